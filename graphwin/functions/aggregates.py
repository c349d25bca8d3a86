"""Aggregates as partials that merge.

An Agg knows how to aggregate raw members into named partial columns, how partials of disjoint (or, where marked, any)
parts merge, and how the final value follows. Indices share and inherit partials; holistic aggregates have none.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

IDEMPOTENT = frozenset({"min", "max", "bool_or", "bool_and", "bit_or", "bit_and", "approx_distinct", "min_by", "max_by"})
HOLISTIC = frozenset({"median", "percentile", "count_distinct", "mode", "collect_list"})


@dataclass(frozen=True)
class Agg:
    """fn over attr. where: a SQL condition on members; by: an attribute whose values split the result into rows.

    Null values count nowhere; a window without a value gives null, counts 0. Attributes may have any name that doesn't begin
    with `_gw_`. Products and moments are doubles."""

    fn: str
    attr: str | None = None
    alias: str = "value"
    where: str | None = None
    by: str | None = None
    attr2: str | None = None
    n: int | None = None

    def __post_init__(self):
        if self.fn not in FUNCTIONS and self.fn not in HOLISTIC:
            raise ValueError(f"unknown aggregate {self.fn}")
        if self.attr is None and self.fn not in ("count", "count_if"):
            raise ValueError(f"{self.fn} needs an attribute")

    @property
    def holistic(self) -> bool:
        return self.fn in HOLISTIC

    @property
    def idempotent(self) -> bool:
        return self.fn in IDEMPOTENT

    @property
    def columns(self) -> list[str]:
        """Vertex attributes that the aggregate reads."""
        own = [c for c in (self.attr, self.attr2, self.by) if c]
        return list(dict.fromkeys(own))

    def _x(self, c: str | None) -> Column:
        col = F.lit(1) if c is None else F.col(c)
        return F.when(F.expr(self.where), col) if self.where else col

    def _parts(self) -> list[tuple[Column, Callable[[Column], Column]]]:
        return FUNCTIONS[self.fn][0](self)

    def partial_names(self) -> list[str]:
        return [f"{self.alias}__{i}" for i in range(len(self._parts()))]

    def partials(self) -> list[Column]:
        """Aggregate expressions over members."""
        return [p.alias(n) for (p, _), n in zip(self._parts(), self.partial_names(), strict=True)]

    def merges(self) -> list[Column]:
        """Aggregate expressions over partial columns of the same names."""
        return [m(F.col(n)).alias(n) for (_, m), n in zip(self._parts(), self.partial_names(), strict=True)]

    def final(self) -> Column:
        return FUNCTIONS[self.fn][1](self, *[F.col(n) for n in self.partial_names()]).alias(self.alias)

    def whole(self) -> Column:
        """The aggregate over raw members, for holistic functions."""
        x = self._x(self.attr)
        made = {
            "median": lambda: F.median(x), "percentile": lambda: F.percentile(x, (self.n or 50) / 100), "count_distinct": lambda: F.count_distinct(x),
            "mode": lambda: F.mode(x, True), "collect_list": lambda: F.sort_array(F.collect_list(x)),
        }
        return made[self.fn]().alias(self.alias)


def _one(agg_of: Callable, merge: Callable | None = None):
    return lambda a: [(agg_of(a._x(a.attr)), merge or agg_of)]


def _moment_parts(a: Agg):
    """n, sums, and second moments around each part's own means, found by the engine's stable aggregates, beside the sums of
    n x mean x mean: all of them merge by adding up, and only the spread between parts is a difference of sums."""
    x = a._x(a.attr).cast("double")
    y = a._x(a.attr2).cast("double") if a.attr2 else x
    known = x.isNotNull() & y.isNotNull()
    x, y = F.when(known, x), F.when(known, y)
    n = F.count(x).cast("double")
    pairs = [(x, x)] + ([(x, y), (y, y)] if a.attr2 else [])
    sums = [n, F.sum(x)] + ([F.sum(y)] if a.attr2 else [])
    return [(c, F.sum) for c in sums + [F.covar_pop(p, q) * n for p, q in pairs] + [F.sum(p) * F.sum(q) / n for p, q in pairs]]


def _moments(ddof: int, root: bool):
    def final(a, n, sx, within, between):
        v = F.when(n > ddof, F.greatest((within + between - sx * sx / n) / (n - ddof), F.lit(0.0)))
        return F.sqrt(v) if root else v

    return _moment_parts, final


def _bivariate(kind: str):
    def final(a, n, sx, sy, wxx, wxy, wyy, bxx, bxy, byy):
        cov, vx, vy = wxy + bxy - sx * sy / n, wxx + bxx - sx * sx / n, wyy + byy - sy * sy / n
        if kind == "covar_pop":
            return cov / n
        return F.when((vx > 0) & (vy > 0), cov / F.sqrt(vx * vy)) if kind == "corr" else F.when(vx > 0, cov / vx)

    return _moment_parts, final


def _geomean():
    """Mean of logarithms; 0 with a zero and without a negative value, null with a negative one."""

    def parts(a: Agg):
        x = a._x(a.attr).cast("double")
        return [(F.sum(F.when(x > 0, F.log(x))), F.sum), (F.count(x), F.sum), (F.count(F.when(x == 0, 1)), F.sum), (F.count(F.when(x < 0, 1)), F.sum)]

    def final(a, logs, n, zeros, negatives):
        return F.when((n > 0) & (negatives == 0), F.when(zeros > 0, F.lit(0.0)).otherwise(F.exp(logs / n)))

    return parts, final


def _vector(mean: bool):
    def parts(a: Agg):
        return [(F.count(a._x(a.attr)), F.sum)] + [(F.sum(F.get(a._x(a.attr), F.lit(i))), F.sum) for i in range(a.n or 1)]

    def final(a, n, *sums):
        return F.when(n > 0, F.array(*[(s / n if mean else s) for s in sums]))

    return parts, final


def _ordered(pick: Callable, by: Callable):
    """value at the least or greatest attr2, ties by value."""
    return lambda a: [(pick(F.when(a._x(a.attr).isNotNull(), F.struct(F.col(a.attr2 or a.attr).alias("k"), F.col(a.attr).alias("v")))), by)]


def _top(a: Agg):
    n = a.n or 3
    cut = lambda arr: F.slice(F.sort_array(arr, asc=False), 1, n)
    return [(cut(F.collect_list(a._x(a.attr))), lambda c: cut(F.flatten(F.collect_list(c))))]


_same = lambda a, x: x
_count = (lambda a: [(F.count(a._x(a.attr)), F.sum)], lambda a, x: F.coalesce(x, F.lit(0)).cast("long"))
#: fn -> (partials with their merges, final)
FUNCTIONS: dict[str, tuple] = {
    "sum": (_one(F.sum), _same), "count": _count, "count_if": _count, "min": (_one(F.min), _same), "max": (_one(F.max), _same),
    "bool_or": (_one(F.bool_or), _same), "bool_and": (_one(F.bool_and), _same), "bit_or": (_one(F.bit_or), _same), "bit_and": (_one(F.bit_and), _same), "bit_xor": (_one(F.bit_xor), _same),
    "avg": (lambda a: [(F.sum(a._x(a.attr)), F.sum), (F.count(a._x(a.attr)), F.sum)], lambda a, s, n: F.when(n > 0, s / n)),
    "var_pop": _moments(0, False), "var_samp": _moments(1, False), "stddev_pop": _moments(0, True), "stddev_samp": _moments(1, True),
    "corr": _bivariate("corr"), "covar_pop": _bivariate("covar_pop"), "regr_slope": _bivariate("regr_slope"),
    "product": (_one(lambda x: F.product(x.cast("double"))), _same), "geomean": _geomean(),
    "min_by": (_ordered(F.min, F.min), lambda a, s: s["v"]), "max_by": (_ordered(F.max, F.max), lambda a, s: s["v"]), "top_n": (_top, _same),
    "approx_distinct": (lambda a: [(F.hll_sketch_agg(a._x(a.attr)), F.hll_union_agg)], lambda a, s: F.coalesce(F.hll_sketch_estimate(s), F.lit(0).cast("long"))),
    "vector_sum": _vector(False), "vector_mean": _vector(True),
}
