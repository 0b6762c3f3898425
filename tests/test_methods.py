"""Worked examples on a small graph, and properties that hold for any."""

import os
import random
import re

import pytest
from pyspark.sql import functions as F

from triplefed import metrics
from triplefed import workloads as w
from triplefed.baselines import caching, hashing, khop, mincut
from triplefed.engine import Config, Engine
from triplefed.federation import place
from triplefed.monitor import Monitor, TemplateState, generalise
from triplefed.operators import cap, semijoin, updates
from triplefed.operators.parallel import exchanges, merged_index, run_merged, run_parallel
from triplefed.operators.patterns import MainIndex, run_centralised
from triplefed.operators.semijoin import communication, exact_cardinalities, key_filter, pass_filter, run_distributed
from triplefed.plans.forest import PatternForest
from triplefed.plans.order import order_patterns, probe_cost
from triplefed.plans.tree import build_tree, is_redistributable, pick_core, vertex_scores
from triplefed.query import bgp, canonical, template_of
from triplefed.sources.graphs import content_graph
from triplefed.sparql import parse_sparql
from triplefed.stats import Stats, predicate_scores, suppress_outliers
from triplefed.storage import save

CAMPUS = [
    ("aComp", "subOrg", "alpha"), ("aEng", "subOrg", "alpha"), ("bComp", "subOrg", "beta"),
    ("ada", "member", "aComp"), ("bob", "member", "aEng"), ("cid", "member", "aEng"), ("dee", "member", "bComp"),
    ("ada", "degreeFrom", "beta"), ("cid", "degreeFrom", "beta"), ("ada", "advisedBy", "bob"), ("bob", "employer", "aEng"),
    ("aComp", "type", "dept"), ("aEng", "type", "dept"), ("bComp", "type", "dept"), ("alpha", "type", "univ"), ("beta", "type", "univ"),
]


@pytest.fixture(scope="module")
def campus(spark):
    return save(spark.createDataFrame(CAMPUS, "s string, p string, o string"))


@pytest.fixture(scope="module")
def content(spark, sf):
    return MainIndex(place(content_graph(spark, sf), "random"), both=False).triples()


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def brute(triples, q):
    found = [{}]
    for e in q.patterns:
        new = []
        for b in found:
            for t in triples:
                c, ok = dict(b), True
                for term, value in zip(e, t):
                    if term.startswith("?"):
                        ok = ok and c.setdefault(term, value) == value
                    else:
                        ok = ok and term == value
                if ok:
                    new.append(c)
        found = new
    return sorted({tuple(b[v] for v in q.variables) for b in found}, key=repr)


def test_predicate_scores_by_hand(spark):
    # three subjects of degree 3, 4, 3 and two objects of degree 4 and 3
    t = [("x", "m", "u"), ("y", "m", "u"), ("z", "m", "v"), ("x", "a", "1"), ("x", "b", "2"), ("y", "a", "3"), ("y", "b", "4"), ("y", "c", "5"), ("z", "a", "6"), ("z", "b", "7"), ("u", "d", "8"), ("u", "e", "9"), ("v", "d", "10"), ("v", "e", "11")]
    got = {r["p"]: r for r in predicate_scores(spark.createDataFrame(t, "s string, p string, o string")).collect()}
    assert round(got["m"]["p_s"], 2) == 3.33 and got["m"]["p_o"] == 3.5


def test_local_mean_and_sketch(spark, campus):
    exact = {r["p"]: r for r in predicate_scores(campus).collect()}
    sketch = {r["p"]: r for r in predicate_scores(campus, "sketch").collect()}
    few = {r["p"]: r for r in predicate_scores(campus, "sketch", target=1).collect()}
    one = {r["p"]: r for r in predicate_scores(campus.withColumn("home", F.lit(0)), "local_mean").collect()}
    for p, r in exact.items():
        assert sketch[p]["p_s"] == pytest.approx(r["p_s"]) and one[p]["p_o"] == pytest.approx(r["p_o"]) and sketch[p]["n"] == r["n"] == few[p]["n"]


def test_outliers(spark):
    s = spark.createDataFrame([(f"p{i}", 5.0, 4.0 + i % 2) for i in range(20)] + [("hub", 5.0, 900.0), ("type", 1.0, 1.0)], "p string, p_s double, p_o double")
    got = {r["p"]: r["outlier"] for r in suppress_outliers(s).collect()}
    assert got["hub"] and got["type"] and not any(got[f"p{i}"] for i in range(20))
    assert not any(r["outlier"] for r in suppress_outliers(s.where("p like 'p%'").limit(1)).collect())


def test_vertex_scores_core_and_tree():
    scores = {"subOrg": (3.0, 6.0), "member": (1.0, 4.0), "degreeFrom": (1.0, 5.0), "type": (float("-inf"),) * 2}
    q = bgp("?s member ?d . ?d subOrg ?u . ?s degreeFrom ?u . ?d type dept")
    v = vertex_scores(q, scores)
    assert v["?d"] == 4.0 and v["dept"] == float("-inf") and pick_core(q, scores) == "?u"
    tree = build_tree(q, "?u", scores)
    assert sorted(n.edge for n in tree.nodes) == [0, 1, 2, 3]
    assert [(n.predicate, n.source, n.prop, n.level) for n in tree.nodes if n.predicate in ("subOrg", "member")] == [("subOrg", "?u", "?d", 1), ("member", "?d", "?s", 2)]
    for order in ("far", "bfs", "ascending", "random"):
        assert sorted(n.edge for n in build_tree(q, "?u", scores, order).nodes) == [0, 1, 2, 3]
    assert pick_core(q, {}, None) == "?s" and pick_core(q, {}, {"member": (0, 9.0)}) == "?d"
    assert not is_redistributable(bgp("?a ?p ?b")) and not is_redistributable(bgp("?a x ?b . ?c x ?d"))


def test_propagation_by_hand(spark, campus, monkeypatch):
    # a hash that sends alpha to worker 0 and beta to worker 1
    monkeypatch.setattr(cap, "worker_of", lambda c, n, kind: F.when(F.col(c) == "alpha", 0).otherwise(1).cast("int"))
    q = bgp("?d subOrg ?u . ?s member ?d")
    tree = build_tree(q, "?u", {"subOrg": (1.0, 9.0), "member": (1.0, 2.0)})
    got = {path[-1][1]: rows(df) for path, df in cap.module_plan(campus, tree, 2).items()}
    assert got["subOrg"] == [(0, "alpha", "aComp"), (0, "alpha", "aEng"), (1, "beta", "bComp")]
    assert got["member"] == [(0, "aComp", "ada"), (0, "aEng", "bob"), (0, "aEng", "cid"), (1, "bComp", "dee")]


def test_union_of_copies_answers_a_third_query(spark, campus):
    forest = PatternForest()
    scores = {"subOrg": (1.0, 9.0), "member": (1.0, 2.0), "degreeFrom": (1.0, 3.0), "type": (float("-inf"),) * 2}
    for text in ("?d subOrg ?u . ?d type dept . ?s member ?d", "?s degreeFrom ?u . ?u type univ"):
        q = bgp(text)
        cap.redistribute(campus, build_tree(q, "?u", scores), forest.get, forest.add, 3)
    five = bgp("?d subOrg ?u . ?d type dept . ?s member ?d . ?u type univ . ?x degreeFrom ?u")
    tree = build_tree(five, "?u", scores)
    match = forest.match(tree)
    assert match is not None
    assert rows(run_parallel(five, tree, match)) == rows(run_centralised(campus, five)) == sorted(brute(CAMPUS, five), key=repr)
    # a constant at a vertex that was copied as a variable, and one at a missing path
    some = bgp("?d subOrg alpha . ?s member ?d")
    tree = build_tree(some, "alpha", scores)
    assert rows(run_parallel(some, tree, forest.match(tree))) == brute(CAMPUS, some)
    other = bgp("?s member ?d . ?d subOrg ?u")
    assert forest.match(build_tree(other, "?d", scores)) is None
    # the same predicate at another level is another module
    before = len(forest.modules)
    cap.redistribute(campus, build_tree(other, "?s", scores), forest.get, forest.add, 3)
    assert len(forest.modules) == before + 2


def test_canonical_forms():
    a, b = bgp("?x p ?y . ?y q c/1"), bgp("?b q c/1 . ?a p ?b")
    assert canonical(a)[0] == canonical(b)[0] != canonical(bgp("?x p ?y . ?y q c/2"))[0]
    assert template_of(a)[0] == template_of(bgp("?x p ?y . ?y q c/2"))[0]
    rng = random.Random(1)
    for q in w.QUERIES.values():
        e = list(q.patterns)
        rng.shuffle(e)
        names = {v: f"?n{i}" for i, v in enumerate(rng.sample(q.variables, len(q.variables)))}
        assert canonical(type(q)(tuple(e)).bind(names))[0] == canonical(q)[0]


def test_monitor_fires_above_the_threshold():
    m = Monitor("reactive", 3)
    q = bgp("?x p c/1")
    assert [m.observe(q) is not None for _ in range(5)] == [False, False, False, True, True]
    m = Monitor("proactive", 3)
    fired = [m.observe(bgp(f"?x p c/{i}")) for i in range(4)]
    assert fired[:3] == [None] * 3 and fired[3] is not None


def test_proactivity():
    template, _ = template_of(bgp("?a p c/1"))
    state = TemplateState()
    for values in ((("?v0", "c/1"), ("?v1", "?")), (("?v0", "c/2"), ("?v1", "?")), (("?v0", "c/2"), ("?v1", "d"))):
        state.observe(values)
    vertices = template.graph.vertices
    assert set(vertices) == {"?v0", "?v1"}
    assert "c/2" in generalise(template, state, 2).vertices and "?v1" in generalise(template, state, 2).vertices
    assert generalise(template, state, 1).vertices == vertices and "c/2" in generalise(template, state, float("inf")).vertices


def test_all_modes_agree(spark, content):
    s = Stats(predicate_scores(content))
    for name, q in w.CONTENT_QUERIES.items():
        want = rows(run_centralised(content, q))
        for strategy in ("auto", "broadcast_keys", "shuffle", "bloom", "plain"):
            assert rows(run_distributed(content, q, s, strategy)) == want, (name, strategy)
        for n in (1, 3, 8):
            for candidates in ("all", "entities"):
                tree = build_tree(q, pick_core(q, s.scores, s.raw, candidates, w.LITERALS), s.scores)
                plans = cap.module_plan(content, tree, n)
                assert rows(run_parallel(q, tree, lambda i: plans[tree.path(i)])) == want, (name, n, candidates)
        cut = probe_cost(q, order_patterns(q, s), s)
        assert cut >= 0


def test_baselines_agree(spark, content):
    assign = save(mincut.mincut_partition(content, 4, 4))
    random_cut = metrics.edge_cut(content, khop.hash_assignment(content, 4)).collect()[0]
    cut = metrics.edge_cut(content, assign).collect()[0]
    assert cut["cut"] < random_cut["cut"] and cut["balance"] < 1.6
    two = khop.khop_partition(content, 2, hub_cutoff=False)
    by_s = place(content.drop("home"), "hash_s", 4)
    cache, joins = caching.ResultCache(), caching.MaterializedJoins()
    for name, q in w.CONTENT_QUERIES.items():
        want = rows(run_centralised(content, q))
        assert rows(khop.khop_query(two, content, q)[1]) == want, name
        assert rows(hashing.hash_query(by_s, q)[1]) == want, name
        for _ in range(2):
            assert rows(cache.answer(q, lambda x: run_distributed(content, x))) == want
            assert rows(joins.answer(content, q)) == want
    assert cache.hits == 5 and joins.hits >= 5
    assert hashing.hash_query(by_s, w.QUERIES["Y1"])[0] == "parallel" and hashing.hash_query(by_s, w.QUERIES["Y3"])[0] == "distributed"
    held = khop.khop_partition(content, 2, assign=assign, hub_cutoff=False)
    assert rows(khop.khop_query(held, content, w.QUERIES["Y5"], assign=assign)[1]) == rows(run_centralised(content, w.QUERIES["Y5"]))
    assert khop.centre(w.QUERIES["Y5"], 2, require_type=True) is None


def held_modules(t, tree, n, close=None):
    held = {}
    cap.redistribute(t, tree, held.get, lambda m: held.__setitem__(m.path, m), n, close_cycles=close)
    return {i: held[cap.in_space(tree.path(i), close)] for i in range(len(tree.nodes))}


def test_parallel_plans_have_no_exchange(spark, content):
    for name in ("Y1", "Y3", "Y5"):
        q = w.QUERIES[name]
        tree = w.reference_tree(q)
        match = held_modules(content, tree, 5)
        got = run_parallel(q, tree, match)
        assert exchanges(got) == 0 and rows(got) == rows(run_centralised(content, q))
        merged = merged_index({m.path: m for m in match.values()})
        assert rows(run_merged(q, tree, merged, 5)) == rows(run_centralised(content, q))


def test_a_constant_core_reads_one_worker(spark, content):
    q = bgp("?d source source/src3 . ?d lang ?l")
    tree = build_tree(q, "source/src3", w.REFERENCE_SCORES)
    match = held_modules(content, tree, 5)
    got = run_parallel(q, tree, match)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert exchanges(got) == 0 and plan.count("SelectedBucketsCount: 1 out of 5") == 2
    assert rows(got) == rows(run_centralised(content, q))


def test_closed_cycles_serve_their_template_alone(spark):
    t = save(spark.createDataFrame([("a", "p", "b"), ("b", "q", "c"), ("c", "r", "a"), ("d", "p", "e"), ("e", "q", "f"), ("g", "p", "b")], "s string, p string, o string").withColumn("home", F.lit(0)))
    cycle, path = bgp("?x p ?y . ?y q ?z . ?z r ?x"), bgp("?x p ?y . ?y q ?z")
    e = Engine(t, Config(workers=3, close_cycles=True), index=False)
    e.redistribute(cycle)
    for q in (cycle, path, bgp("?x p b . b q ?z . ?z r ?x")):
        assert rows(e.answer(q)) == rows(e.central(q)), q
    assert e.plan(cycle).mode == "parallel" and e.plan(path).mode == "distributed"


def test_queries_of_many_patterns(spark):
    chain = [(f"v{i}", f"p{i % 3}", f"v{i + 1}") for i in range(16)]
    t = spark.createDataFrame(chain, "s string, p string, o string").withColumn("home", F.lit(0))
    q = bgp(" . ".join(f"?a{i} p{i % 3} ?a{i + 1}" for i in range(14)))
    e = Engine(save(t), Config(workers=2, freq=0), index=False)
    assert e.run([q, q]) == [1, 1] and e.log[1]["mode"] == "parallel"
    star = bgp(" . ".join(f"?x p ?y{i}" for i in range(15)))
    assert canonical(star)[0] == canonical(bgp(" . ".join(f"?c p ?z{14 - i}" for i in range(15))))[0]


def test_equal_queries_fill_a_template_alike():
    a, b = bgp("?x p c/1 . ?x p c/2"), bgp("?u p c/2 . ?u p c/1")
    assert template_of(a) == template_of(b)


def test_any_root(spark, content):
    q = w.QUERIES["Y5"]
    for search in ("core", "any"):
        e = Engine(content, Config(workers=3, root_search=search), index=False)
        other = next(v for v in q.vertices if v.startswith("?") and v != e.tree_of(q).root)
        cap.redistribute(content, build_tree(q, other, e.stats.scores), e.forest.get, e.forest.add, 3)
        assert e.plan(q).mode == ("parallel" if search == "any" else "distributed")
        assert rows(e.answer(q)) == rows(e.central(q))


def test_key_filter_lets_all_keys_through(spark):
    keys = spark.range(0, 3000, 3).select(F.concat(F.lit("k"), "id").alias("k"))
    every = spark.range(3000).select(F.concat(F.lit("k"), "id").alias("k"), "id")
    got = {r["id"] for r in pass_filter(every, ["k"], key_filter(keys, 1 << 16), 1 << 16).collect()}
    assert got >= set(range(0, 3000, 3)) and len(got) < 1200


def test_order_looks_at_all_orders(spark, content):
    from triplefed.plans.order import Relation, order_relations

    # from 1: joining 0 first would multiply
    r = [Relation(1000, {"a": 10, "b": 1000}), Relation(10, {"a": 10, "c": 10}), Relation(1000, {"c": 1000, "d": 1000}), Relation(1000, {"d": 1000, "b": 1000})]
    assert order_relations(r) == [1, 2, 3, 0]
    assert sorted(order_relations(r * 4)) == list(range(16))
    q = w.QUERIES["Y5"]
    n = exact_cardinalities(content, q)
    assert n == [content.where(f"p = '{e.p}'" + ("" if e.o.startswith("?") else f" AND o = '{e.o}'")).count() for e in q.patterns]
    assert rows(run_distributed(content, q, Stats(predicate_scores(content)), cardinalities=n)) == rows(run_centralised(content, q))


def test_engine_updates_write_deltas(spark, content):
    q = w.QUERIES["Y5"]
    e = Engine(content, Config(workers=4))
    e.redistribute(q)
    before = {p: rows(m.df) for p, m in e.forest.modules.items()}
    want = rows(e.central(q))
    batches = save(updates.split_batches(content, 5, 2))
    n = [e.delete(batches.where(f"batch = {k}")) for k in range(2)]
    assert sum(n) == batches.count() and e.delete(batches) == 0
    again = cap.module_plan(e.triples, e.tree_of(q), 4)
    assert {p: rows(m.df) for p, m in e.forest.modules.items()} == {p: rows(df) for p, df in again.items()}
    got = e.answer(q)
    assert e.plan(q).mode == "parallel" and exchanges(got) == 0 and rows(got) == rows(e.central(q))
    assert [e.insert(batches.where(f"batch = {k}")) for k in range(2)] == n and e.insert(batches) == 0
    assert {p: rows(m.df) for p, m in e.forest.modules.items()} == before and rows(e.answer(q)) == want
    untouched = {p: m.table for p, m in e.forest.modules.items()}
    e.delete(content.where("p = 'lang'").limit(3))
    assert untouched == {p: m.table for p, m in e.forest.modules.items()}


def test_updates_equal_recomputation(spark, content):
    t = content.select("s", "p", "o")
    tree = w.reference_tree(w.QUERIES["Y5"])
    modules = {p: cap.Module(p, save(df), 0) for p, df in cap.module_plan(t, tree, 4).items()}
    before = {p: rows(m.df) for p, m in modules.items()}
    batch = save(updates.split_batches(t))
    left = save(updates.delete_from_graph(t, batch))
    after = {p: cap.Module(p, df, 0) for p, df in updates.apply_deletes(modules, batch).items()}
    again = cap.module_plan(left, tree, 4)
    assert {p: rows(m.df) for p, m in after.items()} == {p: rows(df) for p, df in again.items()}
    whole = save(updates.insert_into_graph(left, batch))
    assert whole.count() == t.count() == updates.insert_into_graph(whole, batch).count()
    assert {p: rows(df) for p, df in updates.apply_inserts(after, whole, batch, 4).items()} == before


def test_engine_adapts_and_stays_right(spark, content):
    for mode in ("off", "reactive", "proactive"):
        e = Engine(content, Config(workers=4, adaptive=mode, freq=1, proactivity=2), index=False)
        load = w.workload([w.instances(e.triples, q, 2) for q in (w.QUERIES["Y1"], w.QUERIES["Y5"])], 6)
        counts = e.run(load)
        assert counts == [run_centralised(content, q).count() for q in load]
        assert (e.redistributions > 0) == (mode != "off")
        assert ({r["mode"] for r in e.log} == {"distributed"}) == (mode == "off")
    assert e.index_df().count() == len(e.forest.modules) and e.log_df().count() == 6
    assert metrics.converged_at(e.log_df()).collect()[0]["converged_at"] is not None
    e.delete(content.where("p = 'role'").limit(5))
    q = load[-1]
    assert rows(e.answer(q)) == rows(e.central(q))


def test_budget(spark, content):
    q = w.QUERIES["Y5"]
    none = Engine(content, Config(workers=4, rho_max=0.0), index=False)
    assert none.redistribute(q) is None
    tight = Engine(content, Config(workers=4, rho_max=0.01, precheck=True), index=False)
    assert tight.redistribute(q) is None and tight.ratio == 0
    loose = Engine(content, Config(workers=4, rho_max=0.01, precheck=False), index=False)
    assert loose.redistribute(q).added and loose.ratio > 0.01
    wide = Engine(content, Config(workers=4, rho_max=5.0), index=False)
    assert wide.redistribute(q).added and wide.ratio <= 5.0


def test_communication(spark):
    t = spark.createDataFrame([("a", "p", "b", 0), ("c", "p", "b", 1), ("b", "q", "d", 1)], "s string, p string, o string, home int")
    r = communication(t, bgp("?x p ?y . ?y q ?z"), 2).collect()[0]
    assert (r["keys_sent"], r["key_bytes"], r["candidates_sent"], r["candidate_bytes"], r["result_rows"]) == (2, 2, 1, 2, 2)


def test_gini(spark):
    g = lambda *x: metrics.gini(spark.createDataFrame([(i, v) for i, v in enumerate(x)], "worker int, load long")).collect()[0]["gini"]
    assert g(5, 5, 5, 5) == 0 and g(0, 0, 0, 8) == 0.75 and g(0, 0) == 0


def test_edges_of_patterns(spark):
    t = spark.createDataFrame([("a", "p", "a"), ("a", "p", "b"), ("a", "q", "b")], "s string, p string, o string")
    triples = [tuple(r) for r in t.collect()]
    for text in ("?x p ?x", "a ?p b", "?x p ?y . ?x q ?y", "?x p ?y . ?z q ?w", "a p b . ?x q ?y"):
        q = bgp(text)
        assert rows(run_centralised(t, q)) == brute(triples, q), text
        assert rows(run_distributed(t, q)) == brute(triples, q), text
    empty = t.limit(0)
    assert rows(run_centralised(empty, bgp("?x p ?y"))) == []


def test_sparql(spark, campus):
    run = lambda text: rows(parse_sparql(text).run(campus))
    assert run("SELECT ?d WHERE { ?d subOrg alpha . FILTER(?d != aComp) }") == [("aEng",)]
    assert run("SELECT (COUNT(*) AS ?n) WHERE { ?s member ?d }") == [(4,)]
    assert run("ASK { alpha member ?x }") == [(False,)]
    with pytest.raises(ValueError):
        parse_sparql("DELETE WHERE { ?a b ?c }")


@pytest.mark.parametrize("name", ["documents", "embeddings", "pages"])
def test_large_tables_are_read_whole(spark, sf, name):
    from triplefed.queries import surface

    queries, sql = surface.queries()
    got, given = queries[f"src_parquet_{name}"](spark, sf), spark.read.parquet(f"{sf}/{name}.parquet")
    assert got.columns == given.columns and got.exceptAll(given).isEmpty() and given.exceptAll(got).isEmpty()
    assert sql[f"src_parquet_{name}"] == f"SELECT * FROM {name}"


@pytest.mark.parametrize("pushed", ["false", "true"])
def test_python_source_in_sessions_with_and_without_pushdown(spark, content, pushed):
    from triplefed.sources.datasource import round_trip

    some = content.where("p IN ('lang', 'role')").select("s", "p", "o")
    key, before = "spark.sql.python.filterPushdown.enabled", spark.conf.get("spark.sql.python.filterPushdown.enabled", "false")
    spark.conf.set(key, pushed)
    try:
        got = round_trip(spark, some)
        assert sorted(got.collect()) == sorted(some.collect())
        assert got.where("p = 'lang' AND p <> 'role'").count() == some.where("p = 'lang'").count() > 0
        assert got.where("p = 'lang' AND p = 'role'").count() == 0
    finally:
        spark.conf.set(key, before)


@pytest.fixture(scope="module")
def crowded(spark, sf, tmp_path_factory):
    """The given tables with 400 times the customers in the same nations, so that measured scores give other trees."""
    import shutil

    at = tmp_path_factory.mktemp("crowded")
    shutil.copytree(sf, at, dirs_exist_ok=True)
    c = spark.read.parquet(f"{sf}/customer.parquet")
    more = c.crossJoin(spark.range(400)).withColumn("c_custkey", F.col("c_custkey") + 1000 * F.col("id")).drop("id")
    more.coalesce(1).write.parquet(str(at / "made"))
    (at / "customer.parquet").chmod(0o644)
    shutil.copy(next((at / "made").glob("*.parquet")), at / "customer.parquet")
    return str(at)


def test_copies_that_are_compared_follow_the_stated_tree(spark, crowded):
    from triplefed.queries import methods

    assert methods.measured_tree(spark, crowded, "W08").root != w.reference_tree(w.QUERIES["W08"]).root
    want = {cap.module_id(p) for p in cap.tree_paths(w.reference_tree(w.QUERIES["W08"]))}
    q = methods.queries()[0]
    assert {r["module_id"] for r in q["cap_modules_W08"](spark, crowded).collect()} == want
    assert sorted(q["par_W08"](spark, crowded).collect()) == sorted(q["bgp_W08"](spark, crowded).collect())


def test_sessions_may_be_shaped_by_given_scores(spark, crowded):
    from triplefed import experiments as x
    from triplefed.queries.methods import graph

    load = [w.QUERIES["W08"]] * 3
    e = Engine(graph(spark, crowded, "shop"), Config(freq=1, statistics="exact", scores=w.REFERENCE_SCORES), index=False)
    e.run(load)
    assert set(e.forest.modules) == set(x.rehearse(load, Config(freq=1)).forest.modules) != set()


def test_shop_graph_of_repeated_lines_is_a_set_and_writes_nothing(spark, sf, tmp_path, monkeypatch):
    import shutil

    import duckdb

    from triplefed import storage
    from triplefed.queries import methods
    from triplefed.sources.graphs import TABLES, graph_sql

    shutil.copytree(sf, tmp_path, dirs_exist_ok=True)
    lines = spark.read.parquet(f"{sf}/lineitem.parquet").limit(40)
    other = lines.limit(9).withColumn("l_returnflag", F.lit("Z")).withColumn("l_shipdate", F.expr("l_shipdate + INTERVAL 1 DAY"))
    gaps = lines.limit(7).withColumn("l_suppkey", F.lit(None).cast("long"))
    blank = lines.limit(5).withColumn("l_returnflag", F.lit(None).cast("string")).withColumn("l_shipdate", F.lit(None).cast("timestamp"))
    lines.unionByName(lines).unionByName(other).unionByName(gaps).unionByName(blank).coalesce(1).write.parquet(str(tmp_path / "made"))
    (tmp_path / "lineitem.parquet").chmod(0o644)
    shutil.copy(next((tmp_path / "made").glob("*.parquet")), tmp_path / "lineitem.parquet")
    monkeypatch.setattr(storage, "new_folder", lambda spark: pytest.fail("a folder was written"))
    got = methods.graph(spark, str(tmp_path), "shop").select("s", "p", "o").collect()
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet'")
    # a null in a concatenation is skipped there, and leaves the triple out here
    want = c.execute(f"WITH lineitem AS (SELECT * FROM main.lineitem WHERE l_suppkey IS NOT NULL AND l_returnflag IS NOT NULL) SELECT s, p, o FROM ({graph_sql('shop')})").fetchall()
    assert len(got) == len({*map(tuple, got)}) and {*map(tuple, got)} == {*want}


def test_scores_and_degrees_by_stars_are_those_of_the_triples(spark, sf, tmp_path):
    import shutil

    from triplefed.federation import place
    from triplefed.queries import methods
    from triplefed.sources.graphs import LINE_KEY, lines_once, shop_graph, shop_stars
    from triplefed.stats import degrees, star_degrees

    shutil.copytree(sf, tmp_path, dirs_exist_ok=True)
    assert not lines_once(spark, sf)  # one line of the smallest tables comes twice
    lines = spark.read.parquet(f"{sf}/lineitem.parquet").dropDuplicates(list(LINE_KEY)).limit(700)
    blank = lines.limit(5).withColumns({"l_linenumber": F.lit(77), "l_returnflag": F.lit(None).cast("string"), "l_shipdate": F.lit(None).cast("timestamp")})
    gaps = lines.limit(4).withColumn("l_suppkey", F.lit(None).cast("long"))
    lines.unionByName(blank).unionByName(gaps).coalesce(1).write.parquet(str(tmp_path / "made"))
    (tmp_path / "lineitem.parquet").chmod(0o644)
    shutil.copy(next((tmp_path / "made").glob("*.parquet")), tmp_path / "lineitem.parquet")
    assert lines_once(spark, str(tmp_path))
    t, stars = save(place(shop_graph(spark, str(tmp_path)), "random")), shop_stars(spark, str(tmp_path))
    assert rows(shop_graph(spark, str(tmp_path), True)) == rows(t.select("s", "p", "o"))
    assert [s.alone for s in stars].count(True) == 1
    for method in ("exact", "local_mean"):
        close = lambda df: [tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in rows(df)]
        assert close(predicate_scores(None, method, stars=stars)) == close(predicate_scores(t, method))
    assert rows(star_degrees(stars)) == rows(degrees(t))
    for end in "so":
        assert rows(star_degrees(stars, end)) == rows(t.groupBy(end).count())
    methods.release(spark)


def _spark_files(spark) -> int:
    """Shuffle files that the session holds."""
    return len([*spark.sparkContext._jvm.scala.jdk.javaapi.CollectionConverters.asJava(spark.sparkContext._jsc.sc().env().blockManager().diskBlockManager().getAllFiles())])


def test_written_tables_leave_no_shuffle_files(spark):
    from triplefed import storage

    before = spark.conf.get(storage.CLEAN, None)
    held = _spark_files(spark)
    out = storage.save(spark.range(1000).selectExpr("id % 100 AS a").distinct())
    assert out.count() == 100
    with storage.tidy(spark), storage.tidy(spark):
        assert spark.range(1000).selectExpr("id % 90 AS a").distinct().count() == 90
    assert _spark_files(spark) <= held + 4 * 2  # the count of what was written
    assert spark.conf.get(storage.CLEAN, None) == before
    at = os.path.dirname(out.inputFiles()[0].removeprefix("file:").replace("//", ""))
    assert os.path.isdir(at)
    storage.discard(out)
    assert not os.path.exists(at)


def test_sides_with_few_rows_leave_the_others_in_place(spark):
    """Where the right side has few rows, a round writes nothing and shuffles no left row; where it has many, all is as before."""
    rows = [(f"l{i}", "of", f"o{i % 40}", i % 3) for i in range(400)] + [(f"o{i}", "by", f"c{i % 7}", i % 2) for i in range(40)] + [(f"c{i}", "in", f"n{i % 2}", 0) for i in range(7)]
    t = spark.createDataFrame(rows, "s string, p string, o string, home int")
    q = bgp("?l of ?o . ?o by ?c . ?c in n1")
    want = sorted((f"l{i}", f"o{i % 40}", f"c{(i % 40) % 7}") for i in range(400) if (i % 40) % 7 % 2)
    wrote = []
    out = semijoin.run_distributed(t, q, write=lambda df: wrote.append(df) or df)
    assert not wrote and "SortMergeJoin" not in out._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, out.select("l", "o", "c").collect())) == want
    few, semijoin._few = semijoin._few, lambda rows, n=0: False
    try:
        out = semijoin.run_distributed(t, q, write=lambda df: wrote.append(df) or df)
        assert len(wrote) == 1 and sorted(map(tuple, out.select("l", "o", "c").collect())) == want
        many = sorted(map(tuple, semijoin.communication(t, q, 3, write=lambda df: df).collect()))
    finally:
        semijoin._few = few
    wrote.clear()
    assert sorted(map(tuple, semijoin.communication(t, q, 3, write=lambda df: wrote.append(df) or df).collect())) == many
    assert len(wrote) == 5  # askers and counts of both rounds, result rows of the first
    keys = {(f"o{i % 40}", i % 3) for i in range(400)}
    sent = [(f"o{i}", f"c{i % 7}") for i in range(40) for k in range(3) if (f"o{i}", k) in keys and k != i % 2]
    assert many[0] == (1, len(keys) * 2, sum(len(o) for o, _ in keys) * 2, len(sent), sum(len(a) + len(b) for a, b in sent), 400)


def test_traffic_between_more_workers_than_bits(spark):
    rows = [(f"a{i}", "p", f"b{i % 5}", i) for i in range(200)] + [(f"b{i}", "q", "x", 199 - i) for i in range(5)]
    t = spark.createDataFrame(rows, "s string, p string, o string, home int")
    got = semijoin.communication(t, bgp("?a p ?b . ?b q ?x"), 200).collect()[0]
    sent = sum(1 for i in range(200) if i != 199 - i % 5)
    assert tuple(got) == (1, 200 * 199, 2 * 200 * 199, sent, 3 * sent, 200)


def test_batches_hold_only_what_copies_can(spark, monkeypatch):
    """A batch is written of the predicates of the copies alone, and takes from them what the whole batch would."""
    from triplefed.queries import methods

    t = spark.createDataFrame([(f"s{i}", p, f"o{i % 3}") for i in range(60) for p in ("kept", "other")], "s string, p string, o string")
    module = cap.Module((None, ("out", "kept", None)), cap.place_core_edges(cap.edge_rows(t, (None, ("out", "kept", None))), 8), 60)
    wrote = []
    monkeypatch.setattr(methods, "graph", lambda *_: t)
    monkeypatch.setattr(methods, "modules_of", lambda *_, **__: (None, {0: module}))
    monkeypatch.setattr(methods, "save", lambda df: wrote.append(df) or save(df))
    left = {r["src"] for r in methods._update(spark, "", "W07", False).collect()}
    assert {r["p"] for r in wrote[0].select("p").distinct().collect()} == {"kept"}
    gone = {r["s"] for r in updates.split_batches(t).where("p = 'kept'").collect()}
    assert gone and left == {f"s{i}" for i in range(60)} - gone


def test_broadcast_keys_are_numbers(spark):
    """The driver builds what is broadcast: keys go as 8 bytes, whatever their terms are, and the answer is exact."""
    left = spark.createDataFrame([(f"line/{i}-{i % 7}-a", f"x/{i}") for i in range(300)] + [(None, "x/none")], "l string, x string")
    right = spark.createDataFrame([(f"line/{i}-{i % 7}-a", f"order/{i % 50}") for i in range(150, 900)] + [(None, "order/none")], "l string, o string")
    found = semijoin.semi_join_step(left, right, "broadcast_keys")
    sent = re.findall(r"BroadcastExchange HashedRelationBroadcastMode\(List\((input\[0, \w+)", found._jdf.queryExecution().executedPlan().toString())
    assert "input[0, bigint" in sent
    assert rows(found) == sorted((f"line/{i}-{i % 7}-a", f"x/{i}", f"order/{i % 50}") for i in range(150, 300))
