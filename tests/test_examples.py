"""The two worked examples, with their printed answers."""

from pyspark.sql import functions as F

from graphwin.functions.aggregates import Agg
from graphwin.functions.hashing import PRIME, affine_constants
from graphwin.model import KHop, Topological
from graphwin.operators.blockindex import block_query, build_block_index, check_cover
from graphwin.operators.deltaindex import build_delta_index, delta_query
from graphwin.operators.reach import window_pairs
from graphwin.plans.measures import add_count, add_count_direct, block_stats
from graphwin.sources.graphs import tinypath, tinysocial


def named(pairs):
    out = {}
    for r in pairs.collect():
        out.setdefault(chr(65 + r["owner"]), set()).add(chr(65 + r["member"]))
    return {k: "".join(sorted(v)) for k, v in out.items()}


def test_social_windows(spark):
    g = tinysocial(spark)
    one = named(window_pairs(g, KHop(1)))
    assert one["B"] == "ABDF" and one["C"] == "ACDEF" and one["E"] == "ACE"
    assert named(window_pairs(g, KHop(2)))["E"] == "ABCDEF"


def test_social_index(spark):
    g = tinysocial(spark)
    clusters = spark.createDataFrame([(i, i // 3) for i in range(6)], "owner long, cluster long")
    # the example's second cluster keeps D and F together, as any hash does whose least value over {B, D, F} is B's
    of = lambda seed, x: (lambda a, b: (a * x + b) % PRIME)(*affine_constants(1, seed)[0])
    seed = next(s for s in range(1, 99) if of(s + 1, 1) < min(of(s + 1, 3), of(s + 1, 5)))
    ix = build_block_index(g, KHop(1), clusters=clusters, seed=seed)
    s = block_stats(ix).first()
    assert (s["blocks"], s["dense"]) == (7, 3)
    blocks = ix.members.groupBy("block_id").agg(F.array_sort(F.collect_list("member")).alias("m")).join(ix.links.groupBy("block_id").agg(F.array_sort(F.collect_list("owner")).alias("o")), "block_id").collect()
    got = {"".join(chr(65 + x) for x in r["m"]): "".join(chr(65 + x) for x in r["o"]) for r in blocks}
    assert set(got) == {"ADF", "B", "CE", "AC", "D", "E", "F"}
    assert got["ADF"] == "ABC" and got["CE"] == "AC" and got["AC"] == "DEF" and set("AB") <= set(got["B"])
    assert add_count(ix) == 13 and add_count_direct(window_pairs(g, KHop(1))).first()[0] == 20
    assert set(check_cover(ix, window_pairs(g, KHop(1))).values()) == {0}
    posts = {chr(65 + r["id"]): r["value"] for r in block_query(ix, g, [Agg("sum", "attr")]).collect()}
    assert posts["B"] == 0 + 1 + 3 + 5 and posts["E"] == 0 + 2 + 4


def test_path_windows_and_deltas(spark):
    g = tinypath(spark)
    w = named(window_pairs(g, Topological()))
    assert w["D"] == "ABD" and w["E"] == "ABCDE" and w["H"] == "ABDH"
    ix = build_delta_index(g)
    parents = {chr(65 + r["v"]): r["pid"] and chr(65 + r["pid"]) for r in ix.parent.collect()}
    assert parents["E"] == "D" and parents["H"] == "D"
    delta = {(chr(65 + r["v"]), chr(65 + r["member"])) for r in ix.delta.collect()}
    assert delta == {("E", "C"), ("D", "B")}
    for how in ("level", "jump"):
        got = {r["id"]: r["value"] for r in delta_query(ix, g, [Agg("sum", "attr")], how).collect()}
        assert got == {0: 0, 1: 1, 2: 2, 3: 4, 4: 10, 7: 11}
