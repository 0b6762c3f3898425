"""The experiments: each gives a table, over whatever graph and load it is handed.

Times are of this machine at the moment; all else in a table follows from the data and the load. ``rehearse`` says without
any data what a session will do: which queries run parallel, and what is copied when.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed import metrics
from triplefed import workloads as w
from triplefed.baselines import khop, mincut
from triplefed.engine import Config, Engine
from triplefed.federation import place
from triplefed.monitor import Monitor
from triplefed.operators import cap, updates
from triplefed.operators.patterns import MainIndex, run_centralised
from triplefed.operators.semijoin import run_distributed
from triplefed.plans.forest import PatternForest
from triplefed.plans.tree import build_tree, is_redistributable, pick_core
from triplefed.query import QueryGraph, template_of
from triplefed.stats import Stats, predicate_scores, stats_error
from triplefed.storage import save

FOREVER = float("inf")


class Rehearsal(Engine):
    """An engine without data: given scores, it plans, watches and notes copies of no rows."""

    def __init__(self, scores: dict[str, tuple[float, float]], config: Config):
        self.config = config
        self.stats = Stats.__new__(Stats)
        self.stats.scores, self.stats.raw, self.stats.total = scores, {}, 1
        self.forest, self.shapes, self.log = PatternForest(), {}, []
        self.monitor = Monitor(config.adaptive, config.freq, config.proactivity)

    def go(self, load: list[QueryGraph]) -> list[dict]:
        for q in load:
            mode = self.plan(q).mode
            wanted, new = self.monitor.observe(q), []
            if wanted is not None and is_redistributable(wanted):
                new = self.forest.missing(self.tree_of(wanted))
                for path in new:
                    self.forest.add(cap.Module(path, None, 0))
            self.log.append({"seq": len(self.log), "template_id": template_of(q)[0].text, "mode": mode, "n_modules": len(new)})
        return self.log


def rehearse(load: list[QueryGraph], config: Config, scores: dict | None = None) -> Rehearsal:
    out = Rehearsal(scores or w.REFERENCE_SCORES, config)
    out.go(load)
    return out


def _seconds(run: Callable) -> float:
    began = time.time()
    run()
    return time.time() - began


def _spent(df: DataFrame) -> float:
    return _seconds(lambda: df.write.format("noop").mode("overwrite").save())


def _table(spark: SparkSession, rows: Iterable[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(list(rows), schema)


def khop_system(t: DataFrame, k: int = 2, workers: int = 8) -> tuple[DataFrame, DataFrame, frozenset[str], float]:
    """Replicas over a min-cut, owners, predicates that lead to hubs, and the seconds that took."""
    began = time.time()
    spo = t.select("s", "p", "o")
    owners = mincut.mincut_partition(spo, workers, 3)
    stop = save(khop.hubs(spo))
    held = khop.khop_partition(spo, k, owners, workers, hub_vertices=stop)
    return held, owners, khop.hub_predicates(spo, stop), time.time() - began


def startup(t: DataFrame, first: QueryGraph, workers: int = 8) -> DataFrame:
    """System, preprocessing, loading, statistics, all of it, and until the first answer."""
    e = Engine(place(t, "random", workers), Config(workers=workers))
    r = e.startup
    answered = _spent(e.answer(first))
    rows = [("adaptive", r.preprocessing_s, r.load_s, r.statistics_s, r.total_s, r.total_s + answered)]
    held, owners, blocked, spent = khop_system(e.triples, 2, workers)
    loaded = _seconds(lambda: MainIndex(held.drop("worker"), both=False))
    answered = _spent(khop.khop_query(held, e.triples, first, 2, owners, workers, hub_predicates=blocked)[1])
    rows.append(("2-hop", spent, loaded, 0.0, spent + loaded, spent + loaded + answered))
    return _table(t.sparkSession, rows, "system string, preprocessing_s double, load_s double, statistics_s double, total_s double, first_answer_s double")


def session(t: DataFrame, load: list[QueryGraph], config: Config) -> Engine:
    """An engine that has run a load; its statistics are exact if the configuration says so."""
    e = Engine(place(t, "random", config.workers), config)
    e.run(load)
    return e


def thresholds(t: DataFrame, load: list[QueryGraph], freqs: tuple = (0, 1, 3, 5, 10, 20), thetas: tuple = (0, 1, 2, 5, 10, 20, FOREVER)) -> DataFrame:
    """The frequency with boundless proactivity, then proactivity at a frequency of 3."""
    rows = []
    index = MainIndex(place(t, "random"))
    for name, settings in (("freq", [(f, FOREVER) for f in freqs]), ("proactivity", [(3, x) for x in thetas])):
        for freq, theta in settings:
            e = Engine(index.triples(), Config(freq=freq, proactivity=theta, statistics="exact"), index=False)
            e.run(load)
            rows.append((name, float(freq if name == "freq" else theta), *_summary(e)))
    return _table(t.sparkSession, rows, f"parameter string, value double, {SUMMARY}")


SUMMARY = "queries long, parallel long, redistributions long, replica_rows long, ratio double, seconds double"


def _summary(e: Engine) -> tuple:
    return (len(e.log), sum(r["mode"] == "parallel" for r in e.log), sum(r["n_modules"] > 0 for r in e.log), int(e.forest.rows), float(e.ratio), sum(r["exec_s"] + r["redist_s"] for r in e.log))


def cumulative(t: DataFrame, loads: list[list[QueryGraph]], config: Config | None = None) -> DataFrame:
    """Of each system and load, the time so far after each query; the k-hop system's begins with its making."""
    spark, out = t.sparkSession, None
    index = MainIndex(place(t, "random"))
    held, owners, blocked, spent = khop_system(index.triples())
    rows = []
    for k, load in enumerate(loads):
        for mode in ("reactive", "proactive"):
            settings = config or Config()
            e = Engine(index.triples(), Config(**{**settings.__dict__, "adaptive": mode}), index=False)
            e.run(load)
            rows += [(mode, k, r["seq"], r["mode"], r["n_modules"], r["exec_s"], r["redist_s"]) for r in e.log]
        for seq, q in enumerate(load):
            how, answer = khop.khop_query(held, index.triples(), q, 2, owners, hub_predicates=blocked)
            rows.append(("2-hop", k, seq, how, 0, _spent(answer), spent if seq == 0 else 0.0))
    log = _table(spark, rows, "system string, load int, seq long, mode string, n_modules int, exec_s double, redist_s double")
    for (system, k) in sorted({(r[0], r[1]) for r in rows}):
        part = metrics.cumulative(log.where((F.col("system") == system) & (F.col("load") == k))).select(F.lit(system).alias("system"), F.lit(k).alias("load"), "seq", "cum_s")
        out = part if out is None else out.unionByName(part)
    return log.join(out, ["system", "load", "seq"])


def per_query(t: DataFrame, queries: dict[str, QueryGraph]) -> DataFrame:
    """Seconds of each query by semi-joins, on copies, and on k-hop replicas, after all that they rest on was made."""
    index = MainIndex(place(t, "random"))
    e = Engine(index.triples(), Config(statistics="exact"), index=False)
    held, owners, blocked, _ = khop_system(index.triples())
    rows = []
    for name, q in queries.items():
        e.redistribute(q)
        runs = (lambda: e.answer(q), lambda: run_distributed(index.triples(), q, e.stats), lambda: khop.khop_query(held, index.triples(), q, 2, owners, hub_predicates=blocked)[1])  # noqa: B023
        best = [min(_seconds(lambda f=f: f().write.format("noop").mode("overwrite").save()) for _ in range(2)) for f in runs]
        rows.append((name, *best))
    return _table(t.sparkSession, rows, "query string, parallel_s double, semi_join_s double, khop_s double")


def budgets(t: DataFrame, load: list[QueryGraph], rhos: tuple = (0.0, 0.1, 0.25, 0.5, 1.0, FOREVER)) -> DataFrame:
    """What a bound on copies leaves of them, and of the share of parallel queries."""
    index = MainIndex(place(t, "random"))
    rows = []
    for rho in rhos:
        e = Engine(index.triples(), Config(rho_max=rho, statistics="exact"), index=False)
        e.run(load)
        rows.append((rho, *_summary(e), e.ratio <= rho))
    return _table(t.sparkSession, rows, f"rho_max double, {SUMMARY}, within boolean")


def covered_only(t: DataFrame, load: list[QueryGraph]) -> DataFrame:
    """K-hop replication of all triples, and of those alone that a load touches: making, running the load, rows."""
    rows, spo = [], save(t.select("s", "p", "o"))
    for name, part in (("all", spo), ("covered", save(metrics.relevant(spo, load)))):
        held, owners, blocked, spent = khop_system(part)
        run = sum(_spent(khop.khop_query(held, part, q, 2, owners, hub_predicates=blocked)[1]) for q in load)
        rows.append((name, part.count(), held.count(), spent, run, spent + run))
    return _table(t.sparkSession, rows, "triples_of string, triples long, stored long, preprocessing_s double, load_s double, total_s double")


def scale(graphs: list[DataFrame], load: list[QueryGraph]) -> DataFrame:
    """Triples and seconds of a load, graph by graph, and how well a line fits them."""
    rows = []
    for g in graphs:
        e = session(g, load, Config())
        rows.append((e.stats.total, sum(r["exec_s"] + r["redist_s"] for r in e.log)))
    points = _table(graphs[0].sparkSession, rows, "triples long, seconds double")
    return points.crossJoin(metrics.linearity(points))  # one row


def balance(t: DataFrame, load: list[QueryGraph], workers: int = 8) -> DataFrame:
    """Copies and Gini coefficients of all systems on one graph, of what a worker holds in all and of copies."""
    e = session(t, load, Config(workers=workers, statistics="exact"))
    main = e.triples.select(F.col("home").alias("worker"))
    copies = None
    for m in e.forest.modules.values():
        part = m.df.select("worker")
        copies = part if copies is None else copies.unionByName(part)
    held = khop_system(e.triples, 2, workers)[0].select("worker")
    rows = []
    for system, placed in (("adaptive", main if copies is None else main.unionByName(copies)), ("adaptive copies", copies), ("2-hop", held)):
        if placed is not None:
            g = metrics.gini(metrics.loads(placed, workers)).collect()[0]["gini"]
            n = placed.count()
            rows.append((system, n, (n if system == "adaptive copies" else n - e.stats.total) / e.stats.total, float(g)))
    return _table(t.sparkSession, rows, "system string, rows long, replication double, gini double")


def update_throughput(t: DataFrame, queries: list[QueryGraph], batches: int = 50, share: int = 5) -> DataFrame:
    """X11: a fifth of the triples deleted and inserted again in batches, with copies kept up: triples a second."""
    e = Engine(place(t, "random"), Config(statistics="exact"))
    for q in queries:
        e.redistribute(q)
    before = {m.id: m.rows for m in e.forest.modules.values()}
    split = save(updates.split_batches(e.triples, share, batches))
    rows = []
    for op, run in (("delete", e.delete), ("insert", e.insert)):
        n, spent = 0, 0.0
        for k in range(batches):
            began = time.time()
            n += run(split.where(F.col("batch") == k))
            spent += time.time() - began
        rows.append((op, batches, n, spent, n / max(spent, 1e-9), before == {m.id: m.rows for m in e.forest.modules.values()}))
    return _table(t.sparkSession, rows, "op string, batches int, triples long, seconds double, per_second double, as_at_first boolean")


def trees(queries: dict[str, QueryGraph], scores: dict, raw: dict | None = None) -> dict[tuple[str, str], list[tuple]]:
    """The paths that each choice of core and of tree order copies, by query and choice."""
    out: dict[tuple[str, str], list[tuple]] = {}
    for name, q in queries.items():
        for policy in ("all", "variables", "entities"):
            core = pick_core(q, scores, raw, policy, w.LITERALS)
            for order in ("near", "far", "bfs", "ascending"):
                out[name, f"{policy} {order}"] = cap.tree_paths(build_tree(q, core, scores, order))
        for v in q.vertices:
            out[name, f"core {v}"] = cap.tree_paths(build_tree(q, v, scores))
    return out


def ablation(t: DataFrame, chosen: dict[tuple[str, str], list[tuple]]) -> DataFrame:
    """Copied rows of each choice."""
    sizes: dict[tuple, int] = {}
    held: dict[tuple, cap.Module] = {}
    for path in sorted({p[:n] for paths in chosen.values() for p in paths for n in range(2, len(p) + 1)}, key=lambda p: (len(p), repr(p))):
        rows = cap.edge_rows(t, path).select("src", "prop")
        placed = cap.place_core_edges(rows) if len(path) == 2 else cap.propagate(rows, held[path[:-1]].df)
        held[path] = cap.stored(path, placed)
        sizes[path] = held[path].rows
    return _table(t.sparkSession, [(n, c, sum(sizes[p] for p in paths)) for (n, c), paths in chosen.items()], "query string, choice string, replica_rows long")


def statistic_accuracy(t: DataFrame, queries: dict[str, QueryGraph], policies: tuple = ("random", "hash_s", "hash_o"), workers: tuple = (2, 8)) -> DataFrame:
    """Of each placement, the mean relative errors of averaged local scores, and the share of queries whose core is the
    one that exact scores give."""
    exact = save(predicate_scores(t))
    true = Stats(exact)
    rows = []
    for policy in policies:
        for n in workers:
            local = save(predicate_scores(place(t, policy, n), "local_mean"))
            mean = stats_error(exact, local).agg(F.avg("error_s").alias("s"), F.avg("error_o").alias("o")).collect()[0]
            s = Stats(local)
            same = sum(pick_core(q, s.scores, s.raw) == pick_core(q, true.scores, true.raw) for q in queries.values())
            rows.append((policy, n, mean["s"], mean["o"], same / len(queries)))
    return _table(t.sparkSession, rows, "policy string, workers int, error_s double, error_o double, cores_agree double")


def central_rows(t: DataFrame, load: list[QueryGraph]) -> list[int]:
    return [run_centralised(t, q).count() for q in load]
