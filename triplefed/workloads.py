"""Query templates over the two graphs, instances of them, and workloads."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from triplefed.query import QueryGraph, bgp, is_var

#: Predicates whose objects are literals.
LITERALS = frozenset({"segment", "brand", "partKind", "partSize", "status", "priority", "orderYear", "returnFlag", "shipYear", "eventKind", "lang", "source", "quality", "toxic", "plang", "pageLang", "role", "cluster"})

_SHOP = {
    "W01": "?o placedBy customer/7 . ?o priority prio/1-URGENT",
    "W02": "?l ofPart ?p . ?l soldBy ?s . ?s supplies ?p . ?p brand brand/Brand#7",
    "W03": "?o type class/order . ?o placedBy customer/7",
    "W04": "?c custNation nation/3 . ?c type class/customer . ?c segment ?g",
    "W05": "?l type class/line . ?l soldBy supplier/3",
    "W06": "?l ofOrder ?o . ?o placedBy customer/7 . ?l ofPart ?p . ?p brand ?b",
    "W07": "?c type class/customer . ?c custNation ?n . ?n type class/nation . ?n inRegion region/2 . ?c segment ?g",
    "W08": "?l ofOrder ?o . ?o placedBy ?c . ?c custNation ?n . ?l soldBy ?s . ?s suppNation ?n",
    "W09": "?o type class/order . ?o status status/F . ?o orderYear year/1997",
    "W10": "?s suppNation ?n . ?n inRegion region/1",
    "W11": "?s suppNation ?n . ?n inRegion region/1 . ?s type class/supplier . ?s supplies ?p . ?p partKind kind/ECONOMY",
    "W12": "?e byUser ?c . ?e eventKind ekind/purchase . ?c custNation nation/3",
    "WS": "?l ofPart ?p . ?p brand brand/Brand#7 . ?l ofOrder ?o . ?o placedBy ?c . ?c custNation ?n . ?n inRegion region/2",
}
_CONTENT = {
    "Y1": "?d lang lang/fr . ?d source ?r . ?d quality quality/1",
    "Y2": "?d quotes ?b . ?d source ?s",
    "Y3": "?d1 sameText ?d2 . ?d1 source ?s1 . ?d2 source ?s2",
    "Y4": "?p1 onHost ?h . ?p2 onHost ?h . ?p1 pageLang plang/fr",
    "Y5": "?t2 follows ?t1 . ?t1 role role/user . ?t2 role role/assistant . ?t2 inConv ?v",
}
SHOP_QUERIES: dict[str, QueryGraph] = {k: bgp(v, k) for k, v in _SHOP.items()}
CONTENT_QUERIES: dict[str, QueryGraph] = {k: bgp(v, k) for k, v in _CONTENT.items()}
QUERIES = {**SHOP_QUERIES, **CONTENT_QUERIES}


def constants(q: QueryGraph) -> list[str]:
    """Those that instances change: not the classes of type edges."""
    classes = {e.o for e in q.patterns if e.p == "type"}
    return [v for v in q.vertices if not is_var(v) and v not in classes]


def constant_values(t: DataFrame, q: QueryGraph, constant: str, n: int, seed: int = 0) -> list[str]:
    """``n`` distinct values at the constant's vertex, in the order of a hash with the seed."""
    e = next(e for e in q.patterns if constant in (e.s, e.o))
    column = "o" if e.o == constant else "s"
    values = t.where(F.col("p") == e.p).select(F.col(column).alias("v")).distinct()
    return [r["v"] for r in values.orderBy(F.md5(F.concat(F.lit(f"{seed}|"), "v")), "v").limit(n).collect()]


def instances(t: DataFrame, q: QueryGraph, n: int, seed: int = 0) -> list[QueryGraph]:
    """Up to ``n`` queries of the template with other constants; the query alone where it has none."""
    slots = constants(q)
    if not slots:
        return [q]
    values = {c: constant_values(t, q, c, n, seed) for c in slots}
    count = min(n, max(len(v) for v in values.values()))
    return [q.bind({c: values[c][i % len(values[c])] for c in slots}) for i in range(count)]


#: Constants that vary with an instance's number alone, whatever the data: what comes before the number, the least, how many.
_NUMBERED = {"customer/": (1, 100), "supplier/": (1, 10), "nation/": (0, 25), "region/": (0, 5), "year/": (1992, 7), "brand/Brand#": (1, 25)}


def numbered_instances(q: QueryGraph, n: int) -> list[QueryGraph]:
    """Up to ``n`` queries of the template whose constants are counted on from the template's; no data is looked at."""
    out = []
    for i in range(n):
        values = {}
        for c in constants(q):
            for kind, (least, many) in _NUMBERED.items():
                if c.startswith(kind):
                    values[c] = f"{kind}{least + (int(c[len(kind):]) - least + i) % many}"
        out.append(q.bind(values))
    return list(dict.fromkeys(out))


def numbered_load(names: list[str], size: int, each: int = 12, seed: int = 0) -> list[QueryGraph]:
    return workload([numbered_instances(QUERIES[n], each) for n in names], size, seed)


def workload(pools: list[list[QueryGraph]], size: int, seed: int = 0) -> list[QueryGraph]:
    """``size`` picks: each a template, then an instance, both evenly by hash of the place in the sequence."""
    out = []
    for i in range(size):
        h = hashlib.md5(f"{seed}|{i}".encode()).digest()
        pool = pools[int.from_bytes(h[:4], "big") % len(pools)]
        out.append(pool[int.from_bytes(h[4:8], "big") % len(pool)])
    return out


def query_log(events: DataFrame) -> DataFrame:
    """seq, ts, qid, template_id, consts: events as a log of queries, the template by event type, the constant by user."""
    return events.select(F.col("event_id").alias("seq"), "ts", F.concat_ws("|", "event_type", F.concat(F.lit("customer/"), "user_id")).alias("qid"), F.col("event_type").alias("template_id"), F.array(F.concat(F.lit("customer/"), "user_id")).alias("consts"))

#: Exact predicate scores of both graphs at scale 0.01, rounded. Queries that are checked against SQL take
#: the shape of their trees from these, so that the shape doesn't hang on the data; an engine measures its own.
REFERENCE_SCORES = {
    "brand": (59.866, 80.0), "byUser": (3.0, 79.24), "cluster": (1.0, 50.0), "custNation": (19.667, 66.0), "eventKind": (3.0, 2000.0),
    "follows": (3.771, 3.771), "inConv": (3.627, 5.36), "inRegion": (66.0, 6.0), "lang": (2.97, 250.0), "linksTo": (7.616, 4.588),
    "ofOrder": (6.0, 9.07), "ofPart": (6.0, 59.866), "onHost": (7.616, 4.31), "orderYear": (9.0, 10714.286), "pageLang": (7.616, 62.5),
    "partKind": (59.866, 333.333), "partSize": (59.866, 40.0), "placedBy": (9.0, 19.667), "priority": (9.0, 3000.0), "quality": (4.183, 199.5),
    "quotes": (4.077, 1.3), "role": (3.627, 178.667), "sameText": (4.129, 3.671), "segment": (19.667, 300.0), "shipYear": (6.0, 10714.286),
    "soldBy": (6.0, 1119.31), "source": (2.97, 50.0), "status": (9.0, 5000.0), "suppNation": (1119.31, 66.0), "supplies": (1119.31, 59.866), "toxic": (4.183, 199.5),
}


def reference_tree(q: QueryGraph, candidates: str = "all", order: str = "near", force: str | None = None):
    from triplefed.plans.tree import build_tree, pick_core

    return build_tree(q, pick_core(q, REFERENCE_SCORES, None, candidates, LITERALS, force), REFERENCE_SCORES, order)
