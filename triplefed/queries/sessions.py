"""Queries of engine sessions and experiments. What a session does, not how long it takes, is checked: the SQL beside it has
what a rehearsal without data expects, and counts answers and copies in the tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed import experiments as x
from triplefed import metrics, sqlgen
from triplefed import workloads as w
from triplefed.engine import Config, Engine
from triplefed.federation import WORKERS, place_sql
from triplefed.operators import cap
from triplefed.query import QueryGraph
from triplefed.queries.methods import _SCORES, Query, graph, kept, rounded, stats
from triplefed.sources.graphs import graph_sql

#: The registered sessions: graph, templates, queries. Thresholds are the defaults.
SESSIONS = {"content": (tuple(w.CONTENT_QUERIES), 40), "shop": (tuple(w.SHOP_QUERIES), 65)}
SWEPT, BUDGETED = 16, 10
FREQS, THETAS, RHOS = (0, 3), (0, x.FOREVER), (0.0, 0.1, x.FOREVER)
ABLATED = ("Y1", "Y3", "Y5")
POLICIES, COUNTS = ("random", "hash_s", "hash_o"), (2, 8)


def load_of(name: str, size: int | None = None) -> list[QueryGraph]:
    names, all_ = SESSIONS[name]
    return w.numbered_load(list(names), size or all_)


def _engine(spark: SparkSession, sf_dir: str, name: str) -> Engine:
    def make() -> Engine:
        # the SQL beside it has what a rehearsal by these scores copies
        e = Engine(graph(spark, sf_dir, name), Config(statistics="exact", scores=w.REFERENCE_SCORES), index=False)
        e.run(load_of(name))
        return e

    return kept(spark, sf_dir, f"session {name}", make)


@lru_cache
def _rehearsed(name: str, size: int | None = None, freq: int = 3, proactivity: float = 10) -> x.Rehearsal:
    return x.rehearse(load_of(name, size), Config(freq=freq, proactivity=proactivity))


def _log_sql(name: str) -> str:
    log = _rehearsed(name).log
    rows = ", ".join(f"({r['seq']}, '{r['template_id']}', '{r['mode']}', {r['n_modules']})" for r in log)
    return f"(SELECT CAST(seq AS BIGINT) AS seq, template_id, mode, CAST(n_modules AS INT) AS n_modules FROM (VALUES {rows}) AS v(seq, template_id, mode, n_modules))"


def _answers_sql(name: str) -> str:
    """seq, rows of a load: each different query is counted once."""
    load = load_of(name)
    different = list(dict.fromkeys(load))
    at = ", ".join(f"({i}, {different.index(q)})" for i, q in enumerate(load))
    counts = " UNION ALL ".join(f"SELECT {k} AS k, count(*) AS rows FROM ({sqlgen.to_sql(q, name)})" for k, q in enumerate(different))
    return f"(SELECT CAST(seq AS BIGINT) AS seq, rows FROM (VALUES {at}) AS v(seq, k) JOIN ({counts}) USING (k))"


def _copies_sql(name: str, settings: list[tuple[str, float, x.Rehearsal]]) -> str:
    """parameter, value, queries, parallel, redistributions, replica_rows, ratio."""
    paths = [list(e.forest.modules) for *_, e in settings]
    parts, names = cap.paths_sql([p for some in paths for p in some], WORKERS, name)
    sizes = ", ".join(f"n_{names[p]} AS (SELECT count(*) AS n FROM {names[p]})" for p in dict.fromkeys(p for some in paths for p in some))
    out = []
    for (parameter, value, e), some in zip(settings, paths, strict=True):
        rows = " + ".join(f"(SELECT n FROM n_{names[p]})" for p in some) or "0"
        shown = "'Infinity'::DOUBLE" if value == x.FOREVER else f"{float(value)}::DOUBLE"
        out.append(f"SELECT '{parameter}' AS parameter, {shown} AS value, CAST({len(e.log)} AS BIGINT) AS queries, CAST({sum(r['mode'] == 'parallel' for r in e.log)} AS BIGINT) AS parallel, CAST({sum(r['n_modules'] > 0 for r in e.log)} AS BIGINT) AS redistributions, CAST({rows} AS BIGINT) AS replica_rows")
    return f"WITH {parts}, {sizes}, t AS (SELECT count(*) AS triples FROM ({graph_sql(name)})) SELECT *, replica_rows / triples AS ratio FROM ({' UNION ALL '.join(out)}), t"


def _accuracy_sql() -> str:
    """policy, workers, error_s, error_o."""
    placements = [(p, n) for p in POLICIES for n in COUNTS]
    g = f"WITH g AS MATERIALIZED ({graph_sql('content')}), {_SCORES.format(k='', g='g')}"
    out = []
    for i, (policy, n) in enumerate(placements):
        own = _SCORES.format(k="home,", g=f"h{i}")
        for c in "dabn":
            own = own.replace(f"\n{c} AS", f"\n{c}{i} AS").replace("JOIN d USING", f"JOIN d{i} USING")
        g += f", h{i} AS MATERIALIZED (SELECT s, p, o, {place_sql(policy, n)} AS home FROM g), {own}"
        g += f", l{i} AS (SELECT p, sum(p_s) / count(*) AS a_s, sum(p_o) / count(*) AS a_o FROM a{i} JOIN b{i} USING (home, p) GROUP BY p)"
        out.append(f"SELECT '{policy}' AS policy, CAST({n} AS INT) AS workers, round(avg(abs(a_s / p_s - 1)), 6) AS error_s, round(avg(abs(a_o / p_o - 1)), 6) AS error_o FROM a JOIN b USING (p) JOIN l{i} USING (p)")
    return f"{g} {' UNION ALL '.join(out)}"


def _thresholds(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = graph(spark, sf_dir, "content")
    found = x.thresholds(t, load_of("content", SWEPT), FREQS, THETAS)
    return found.withColumn("triples", F.lit(stats(spark, sf_dir, "content").total).cast("long")).drop("seconds")


def _ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = stats(spark, sf_dir, "content", "exact")
    return x.ablation(graph(spark, sf_dir, "content"), x.trees({n: w.QUERIES[n] for n in ABLATED}, s.scores, s.raw))


def _ablation_sql() -> str:
    chosen = x.trees({n: w.QUERIES[n] for n in ABLATED}, w.REFERENCE_SCORES)
    parts, names = cap.paths_sql([p for paths in chosen.values() for p in paths], WORKERS, "content")
    sizes = ", ".join(f"n_{m} AS (SELECT count(*) AS n FROM {m})" for m in names.values())
    rows = " UNION ALL ".join(f"SELECT '{n}' AS query, '{c}' AS choice, CAST({' + '.join(f'(SELECT n FROM n_{names[p]})' for p in paths)} AS BIGINT) AS replica_rows" for (n, c), paths in chosen.items())
    return f"WITH {parts}, {sizes} {rows}"


def queries() -> tuple[dict[str, Query], dict[str, str]]:
    q: dict[str, Query] = {}
    o: dict[str, str] = {}

    def add(name: str, run: Callable[[SparkSession, str], DataFrame], oracle: str | None = None) -> None:
        q[name] = run
        if oracle is not None:
            o[name] = oracle

    for name in SESSIONS:
        log = _log_sql(name)
        add(f"engine_session_{name}", lambda s, d, n=name: _engine(s, d, n).log_df().select("seq", "template_id", "mode", "n_modules", "rows"), f"SELECT seq, template_id, mode, n_modules, rows FROM {log} JOIN {_answers_sql(name)} USING (seq)")
        add(f"mode_share_{name}", lambda s, d, n=name: metrics.mode_share(_engine(s, d, n).log_df()), f"SELECT mode, count(*) AS queries, count(*) / (SELECT count(*) FROM {log}) AS share FROM {log} GROUP BY mode")
        add(f"converged_at_{name}", lambda s, d, n=name: metrics.converged_at(_engine(s, d, n).log_df()), f"SELECT max(seq) AS converged_at FROM {log} WHERE n_modules > 0")
        add(f"cumulative_{name}", lambda s, d, n=name: _cumulative(_engine(s, d, n)), f"SELECT seq, true AS grows, true AS sums_up FROM {log}")
        settings = [("copies", 0.0, _rehearsed(name))]
        add(f"engine_copies_{name}", lambda s, d, n=name: _copies(_engine(s, d, n)), f"SELECT replica_rows, triples, ratio FROM ({_copies_sql(name, settings)})")
        add(f"engine_index_{name}", lambda s, d, n=name: _engine(s, d, n).index_df().select("module_id", "parent_id", "depth", "label", "direction", "const"), _index_sql(name))
    size = SWEPT
    settings = [("freq", float(f), _rehearsed("content", size, f, x.FOREVER)) for f in FREQS] + [("proactivity", float(p), _rehearsed("content", size, 3, p)) for p in THETAS]
    add("x2_thresholds", _thresholds, _copies_sql("content", settings))
    add("x7_budgets", lambda s, d: x.budgets(graph(s, d, "content"), load_of("content", BUDGETED), RHOS).select("rho_max", "queries", "within"), "SELECT * FROM (VALUES " + ", ".join(f"({chr(39) + 'Infinity' + chr(39) if r == x.FOREVER else r}::DOUBLE, CAST({BUDGETED} AS BIGINT), true)" for r in RHOS) + ") AS v(rho_max, queries, within)")
    add("x12_ablation", _ablation, _ablation_sql())
    add("x13_statistics", lambda s, d: rounded(x.statistic_accuracy(graph(s, d, "content").drop("home"), w.CONTENT_QUERIES, POLICIES, COUNTS).drop("cores_agree")), _accuracy_sql())
    return q, o


def _copies(e: Engine) -> DataFrame:
    return e.spark.createDataFrame([(int(e.forest.rows), int(e.stats.total), float(e.ratio))], "replica_rows long, triples long, ratio double")


def _cumulative(e: Engine) -> DataFrame:
    """seq, whether time so far grows, and whether at the end it is all time."""
    from pyspark.sql.window import Window

    log = e.log_df()
    total = log.agg(F.sum(F.col("exec_s") + F.col("redist_s")).alias("total"), F.max("seq").alias("last"))
    before = F.coalesce(F.lag("cum_s").over(Window.orderBy("seq")), F.lit(0.0))  # a session's log
    return metrics.cumulative(log).crossJoin(total).select("seq", (F.col("cum_s") >= before).alias("grows"), ((F.col("seq") < F.col("last")) | (F.abs(F.col("cum_s") - F.col("total")) < 1e-6)).alias("sums_up"))  # one row


def _index_sql(name: str) -> str:
    def text(v) -> str:
        return "NULL" if v is None else f"'{v}'"

    rows = ", ".join(f"('{cap.module_id(p)}', {text(cap.module_id(p[:-1]) if len(p) > 2 else None)}, {len(p) - 1}, '{p[-1][1]}', '{p[-1][0]}', {text(p[-1][2])})" for p in _rehearsed(name).forest.modules)
    return f"SELECT module_id, CAST(parent_id AS VARCHAR) AS parent_id, CAST(depth AS INT) AS depth, label, direction, CAST(const AS VARCHAR) AS const FROM (VALUES {rows}) AS v(module_id, parent_id, depth, label, direction, const)"
