"""A small SQL surface for window queries over registered graphs.

    SELECT id, SUM(p_size) AS total, COUNT(*) AS n OVER KHOP(2, both) FROM parts [WHERE id IN (...)] [USING block]
           [ORDER BY total DESC LIMIT 10]
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphwin.functions.aggregates import Agg
from graphwin.model import KHop, PropertyGraph, Topological, VertexWindowFunction, VertexWindowQuery

_QUERY = re.compile(
    r"^\s*SELECT\s+id\s*,\s*(?P<funcs>.+?)\s+OVER\s+(?P<kind>KHOP|TOPO)\s*(?:\(\s*(?P<args>[^)]*)\))?\s+FROM\s+(?P<graph>\w+)"
    r"(?:\s+WHERE\s+id\s+IN\s*\((?P<ids>[^)]*)\))?(?:\s+USING\s+(?P<strategy>\w+))?(?:\s+ORDER\s+BY\s+(?P<order>\w+)(?P<desc>\s+DESC)?)?(?:\s+LIMIT\s+(?P<limit>\d+))?\s*;?\s*$",
    re.I | re.S,
)
_FUNC = re.compile(r"(\w+)\s*\(\s*(\*|\w+)\s*\)(?:\s+FILTER\s*\(\s*WHERE\s+([^)]*)\))?(?:\s+BY\s+(\w+))?(?:\s+AS\s+(\w+))?", re.I)


def parse_window_query(text: str) -> dict:
    m = _QUERY.match(text)
    if not m:
        raise ValueError(f"not a window query: {text.strip()[:80]}")
    aggs = [Agg(fn.lower(), None if attr == "*" else attr, alias or f"{fn.lower()}_{'all' if attr == '*' else attr}", where or None, by or None) for fn, attr, where, by, alias in _FUNC.findall(m["funcs"])]
    if not aggs:
        raise ValueError("no aggregate")
    args = [a.strip().lower() for a in (m["args"] or "").split(",") if a.strip()]
    window = KHop(int(args[0]), *(args[1:2] or ["out"])) if m["kind"].upper() == "KHOP" else Topological(*(args[:1] or ["ancestors"]))
    ids = [int(x) for x in m["ids"].split(",")] if m["ids"] else None
    return {"graph": m["graph"], "window": window, "aggs": aggs, "ids": ids, "strategy": (m["strategy"] or "auto").lower(), "order": m["order"], "desc": bool(m["desc"]), "limit": int(m["limit"]) if m["limit"] else None}


def register_graph(graph: PropertyGraph) -> None:
    """Views <name>_vertices and <name>_edges."""
    graph.vertices.createOrReplaceTempView(f"{graph.name}_vertices")
    graph.edges.createOrReplaceTempView(f"{graph.name}_edges")


def graph_window_sql(spark: SparkSession, text: str, graphs: dict[str, PropertyGraph], index=None) -> DataFrame:
    q = parse_window_query(text)
    owners = spark.createDataFrame([(i,) for i in q["ids"]], "owner long") if q["ids"] else None
    query = VertexWindowQuery(graphs[q["graph"]], [VertexWindowFunction(q["window"], a) for a in q["aggs"]])
    out = query.run(q["strategy"], owners=owners, index=index)
    if q["order"]:
        out = out.orderBy(F.desc(q["order"]) if q["desc"] else F.asc(q["order"]), "id")
    return out.limit(q["limit"]) if q["limit"] is not None else out
