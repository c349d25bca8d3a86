"""A Python data source of arithmetic graphs: `spark.read.format("synthgraph").option("kind", "dag")...`."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

MODULUS = 1_000_003


class _Span(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, kind: str, n: int, d: int, parts: int):
        self.kind, self.n, self.d, self.parts = kind, n, d, parts

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Span(a, min(a + step, self.n)) for a in range(0, self.n, step)]

    def read(self, span):
        for v in range(span.lo, span.hi):
            for j in range(self.d if self.kind == "dag" else max(self.d // 2, 1)):
                x = (v * 7919 + j * 104_729 + 17) % MODULUS
                if self.kind == "dag":
                    if v:
                        yield (x % v, v)
                else:
                    u = (x * x + 31 * x + 7) % MODULUS % self.n
                    if u != v:
                        yield (min(u, v), max(u, v))


class SynthGraphSource(DataSource):
    """Options: kind (dag or random), n, d, partitions. Rows may repeat."""

    @classmethod
    def name(cls):
        return "synthgraph"

    def schema(self):
        return "src bigint, dst bigint"

    def reader(self, schema):
        o = self.options
        return _Reader(o.get("kind", "dag"), int(o.get("n", "100")), int(o.get("d", "3")), int(o.get("partitions", "4")))
