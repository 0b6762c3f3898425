"""Queries of the relational surface: sources and sinks, filters, joins, aggregates, windows, sets, functions, iteration,
streams, user functions and SPARQL."""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from triplefed import sqlgen
from triplefed import workloads as w
from triplefed.federation import WORKERS, place
from triplefed.functions import udfs
from triplefed.operators import relops
from triplefed.operators.patterns import natural_join, scan_pattern
from triplefed.query import Pattern
from triplefed.queries.methods import graph, stars
from triplefed.sources import datasource, formats
from triplefed.sources.graphs import TABLES, edge_sql, graph_sql, read_table
from triplefed.sparql import parse_sparql
from triplefed.streaming import streams

T = read_table


def _edges(s: SparkSession, d: str, p: str, a: str, b: str) -> DataFrame:
    return scan_pattern(graph(s, d, "shop"), Pattern(f"?{a}", p, f"?{b}"))


def _e(p: str, a: str, b: str) -> str:
    return f"(SELECT s AS {a}, o AS {b} FROM ({edge_sql('shop', p)}))"


#: Columns of the results that are compared by digest; ``:d`` marks doubles, which count to four places.
COLUMNS = {
    **dict.fromkeys(("sink_ntriples", "sink_csv", "sink_json", "sink_orc", "sink_partitioned", "sink_bucketed", "src_pyds", "flt_sample"), "s p o"),
    **dict.fromkeys(("flt_eq", "flt_range", "flt_in", "flt_like", "flt_null", "flt_bool", "flt_regex"), "c_custkey c_acctbal:d"),
    **dict.fromkeys(("flt_exists", "flt_notexists"), "c n"),
    **dict.fromkeys(("join_left", "join_right", "join_full", "join_so"), "c n o"),
    **dict.fromkeys(("join_semi", "join_anti"), "c o"),
    **dict.fromkeys(("join_bhj", "join_shj", "join_smj"), "c_custkey n_name"),
    **dict.fromkeys(("join_cross", "join_nlj", "join_nullsafe"), "n_name r_name"),
    **dict.fromkeys(("agg_degree_in", "agg_degree_out"), "v n"),
    **dict.fromkeys(("agg_rollup", "agg_cube", "agg_gsets"), "p home n"),
    **dict.fromkeys(("set_union_all", "set_union", "set_intersect", "set_intersect_all", "set_except", "set_except_all"), "n"),
    **dict.fromkeys(("iter_khop_2", "iter_khop_4", "iter_reach"), "v hop"),
    "prj_alias": "name region", "prj_expr": "p_partkey twice brand", "prj_distinct": "o_orderpriority o_orderstatus",
    "join_ss": "o c x", "join_oo": "n c s", "join_multi": "s p l", "join_range": "c_custkey band", "join_interval": "event_id view",
    "join_asof": "event_id order_key", "join_self": "x y", "join_skew": "l_orderkey l_returnflag top",
    "agg_count_p": "p n", "agg_distinct_so": "p n_s n_o", "agg_degree_total": "v degree", "agg_avg_std": "c_nationkey mean:d sd:d low:d high:d",
    "agg_sum": "l_suppkey quantity", "agg_mode": "user_id event_type", "agg_pctl": "p_brand median:d", "agg_maxby": "o_custkey largest",
    "agg_collect": "n_regionkey names", "agg_having": "o_custkey n", "agg_filter": "l_suppkey returned n", "agg_pivot": "o_orderpriority F O P",
    "agg_sort": "o_orderstatus first_priority n", "win_rank": "p o rn rk dr nt pr:d cd:d", "win_lag": "seq before after",
    "win_first": "seq first last", "win_cum": "seq cum", "win_mov": "seq last3", "win_range": "seq hour",
    "top_k": "v degree", "top_k_per_p": "p o n", "top_offset": "o_orderkey", "sort_total": "s_suppkey s_acctbal:d",
    "fn_str": "p_partkey joined part swapped low n digest bare", "fn_date": "o_orderkey y m dd", "fn_math": "c_custkey a:d r:d f l:d m p:d",
    "fn_cond": "c_custkey band n", "fn_date_trunc": "event_id hour epoch later", "fn_arr": "vec_id n norm2:d positive", "fn_explode": "item_id i word",
    "fn_map": "o_custkey kinds f", "fn_json": "event_id k k2", "fn_decimal": "o_orderkey price", "fn_struct": "name region", "fn_regex_all": "page_id n",
}
#: Results that are checked together, by what operator they belong to: a row for each with its rows and their digest.
FOLDS = {
    "sink_formats": "sink_ntriples sink_csv sink_json sink_orc sink_partitioned sink_bucketed", "src_python": "src_pyds",
    "flt_values": "flt_eq flt_range flt_in flt_like flt_null flt_bool flt_regex", "flt_exists_not": "flt_exists flt_notexists", "flt_hash_sample": "flt_sample",
    "prj_lists": "prj_alias prj_expr prj_distinct", "join_ends": "join_ss join_so join_oo", "join_composite": "join_multi", "join_outer": "join_left join_right join_full",
    "join_semi_anti": "join_semi join_anti", "join_physical": "join_bhj join_shj join_smj", "join_theta": "join_nlj join_cross", "join_ranges": "join_range join_interval",
    "join_as_of": "join_asof", "join_special": "join_nullsafe join_self join_skew", "agg_counts": "agg_count_p agg_distinct_so", "agg_degrees": "agg_degree_in agg_degree_out agg_degree_total",
    "agg_basic": "agg_avg_std agg_sum agg_mode agg_pctl agg_maxby", "agg_collections": "agg_collect agg_having agg_filter", "agg_grouping": "agg_rollup agg_cube agg_gsets agg_pivot",
    "agg_sorted": "agg_sort", "win_ranks": "win_rank", "win_shifts": "win_lag win_first", "win_frames": "win_cum win_mov win_range", "tops": "top_k top_k_per_p top_offset sort_total",
    "sets": "set_union_all set_union set_intersect set_intersect_all set_except set_except_all", "fn_strings": "fn_str fn_regex_all", "fn_dates": "fn_date fn_date_trunc",
    "fn_numbers": "fn_math", "fn_arrays": "fn_arr fn_explode", "fn_maps": "fn_map", "fn_jsons": "fn_json", "fn_values": "fn_cond fn_decimal fn_struct",
    "iterations": "iter_khop_2 iter_khop_4 iter_reach",
}


def _digest(name: str, df: DataFrame) -> DataFrame:
    """part, n, digest: how many rows, and the sum of a hash of each over all its columns."""
    text = []
    for c in COLUMNS[name].split():
        column, _, kind = c.partition(":")
        value = F.round(F.col(column) * 10000).cast("long") if kind else F.col(column)
        text.append(F.coalesce(value.cast("string"), F.lit("~")))
    h = F.conv(F.substring(F.md5(F.concat_ws("|", *text)), 1, 8), 16, 10).cast("long")
    return df.agg(F.lit(name).alias("part"), F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(h), F.lit(0)).cast("long").alias("digest"))


def _digest_sql(name: str, rows: str) -> str:
    text = []
    for c in COLUMNS[name].split():
        column, _, kind = c.partition(":")
        value = f"CAST(round({column} * 10000) AS BIGINT)" if kind else f'"{column}"'
        text.append(f"coalesce(CAST({value} AS VARCHAR), '~')")
    h = f"('0x' || substr(md5(concat_ws('|', {', '.join(text)})), 1, 8))::BIGINT"
    return f"SELECT '{name}' AS part, count(*) AS n, CAST(coalesce(sum({h}), 0) AS BIGINT) AS digest FROM ({rows})"


def queries() -> tuple[dict[str, Callable[[SparkSession, str], DataFrame]], dict[str, str]]:
    q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
    o: dict[str, str] = {}
    one: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {}
    shop = graph_sql("shop")

    def add(name: str, run: Callable[[SparkSession, str], DataFrame], oracle: str | None = None) -> None:
        if name in COLUMNS:
            one[name] = (run, oracle)
            return
        q[name] = run
        if oracle is not None:
            o[name] = _with_graph(shop, oracle)

    # ---- sources and sinks
    for t in TABLES:
        add(f"src_parquet_{t}", lambda s, d, t=t: T(s, d, t), f"SELECT * FROM {t}")
    for form in ("ntriples", "csv", "json", "orc", "partitioned", "bucketed"):
        add(f"sink_{form}", lambda s, d, f=form: formats.round_trip(graph(s, d, "content"), f), f"SELECT s, p, o FROM ({graph_sql('content')})")
    add("src_pyds", lambda s, d: datasource.round_trip(_shipped(s), graph(s, d, "content")), f"SELECT s, p, o FROM ({graph_sql('content')})")
    # ---- filters
    c = "SELECT c_custkey, c_acctbal FROM customer WHERE "
    for name, cond in {"eq": "c_mktsegment = 'BUILDING'", "range": "c_acctbal BETWEEN 100 AND 5000", "in": "c_nationkey IN (1, 2, 3)", "like": "c_name LIKE '%7%'", "null": "c_acctbal IS NOT NULL", "bool": "NOT (c_nationkey = 3 OR c_acctbal < 0) AND c_custkey > 5"}.items():
        add(f"flt_{name}", lambda s, d, x=cond: T(s, d, "customer").where(x).select("c_custkey", "c_acctbal"), c + cond)
    add("flt_regex", lambda s, d: T(s, d, "customer").where(F.col("c_name").rlike("[13579]$")).select("c_custkey", "c_acctbal"), c + "regexp_matches(c_name, '[13579]$')")
    placed, cust = lambda s, d: _edges(s, d, "placedBy", "o", "c"), lambda s, d: _edges(s, d, "custNation", "c", "n")
    add("flt_exists", lambda s, d: cust(s, d).join(placed(s, d), "c", "left_semi"), f"SELECT * FROM {_e('custNation', 'c', 'n')} x WHERE EXISTS (SELECT 1 FROM {_e('placedBy', 'o', 'c')} y WHERE y.c = x.c)")
    add("flt_notexists", lambda s, d: cust(s, d).join(placed(s, d), "c", "left_anti"), f"SELECT * FROM {_e('custNation', 'c', 'n')} x WHERE NOT EXISTS (SELECT 1 FROM {_e('placedBy', 'o', 'c')} y WHERE y.c = x.c)")
    add("flt_sample", lambda s, d: relops.deterministic_sample(graph(s, d, "shop").select("s", "p", "o"), 20, "s", "p", "o"), "SELECT * FROM g WHERE ('0x' || substr(md5(concat(s, '|', p, '|', o)), 1, 8))::BIGINT % 100 < 20")
    # ---- projections
    add("prj_alias", lambda s, d: T(s, d, "nation").select(F.col("n_name").alias("name"), F.col("n_regionkey").alias("region")), "SELECT n_name AS name, n_regionkey AS region FROM nation")
    add("prj_expr", lambda s, d: T(s, d, "part").select("p_partkey", (F.col("p_size") * 2 + 1).alias("twice"), F.upper("p_brand").alias("brand")), "SELECT p_partkey, p_size * 2 + 1 AS twice, upper(p_brand) AS brand FROM part")
    add("prj_distinct", lambda s, d: T(s, d, "orders").select("o_orderpriority", "o_orderstatus").distinct(), "SELECT DISTINCT o_orderpriority, o_orderstatus FROM orders")
    # ---- joins
    supp = lambda s, d: _edges(s, d, "suppNation", "s", "n")
    prio = lambda s, d: _edges(s, d, "priority", "o", "x")
    add("join_ss", lambda s, d: natural_join(placed(s, d), prio(s, d)), f"SELECT * FROM {_e('placedBy', 'o', 'c')} JOIN {_e('priority', 'o', 'x')} USING (o)")
    add("join_so", lambda s, d: natural_join(placed(s, d), cust(s, d)), f"SELECT * FROM {_e('placedBy', 'o', 'c')} JOIN {_e('custNation', 'c', 'n')} USING (c)")
    add("join_oo", lambda s, d: natural_join(cust(s, d), supp(s, d)), f"SELECT * FROM {_e('custNation', 'c', 'n')} JOIN {_e('suppNation', 's', 'n')} USING (n)")
    three = lambda s, d: natural_join(_edges(s, d, "ofPart", "l", "p"), _edges(s, d, "soldBy", "l", "s"))
    add("join_multi", lambda s, d: natural_join(three(s, d), _edges(s, d, "supplies", "s", "p")), f"SELECT * FROM {_e('ofPart', 'l', 'p')} JOIN {_e('soldBy', 'l', 's')} USING (l) JOIN {_e('supplies', 's', 'p')} USING (s, p)")
    for how, word in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
        add(f"join_{how}", lambda s, d, h=how: cust(s, d).join(placed(s, d), "c", h), f"SELECT * FROM {_e('custNation', 'c', 'n')} {word} JOIN {_e('placedBy', 'o', 'c')} USING (c)")
    add("join_semi", lambda s, d: placed(s, d).join(cust(s, d).where("n = 'nation/3'"), "c", "left_semi"), f"SELECT * FROM {_e('placedBy', 'o', 'c')} WHERE c IN (SELECT c FROM {_e('custNation', 'c', 'n')} WHERE n = 'nation/3')")
    add("join_anti", lambda s, d: placed(s, d).join(cust(s, d).where("n = 'nation/3'"), "c", "left_anti"), f"SELECT * FROM {_e('placedBy', 'o', 'c')} WHERE c NOT IN (SELECT c FROM {_e('custNation', 'c', 'n')} WHERE n = 'nation/3')")
    for name, hint in (("bhj", "broadcast"), ("shj", "shuffle_hash"), ("smj", "merge")):
        # nation has as many rows as there are nations
        add(f"join_{name}", lambda s, d, h=hint: T(s, d, "customer").join(T(s, d, "nation").hint(h), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name"), "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
    add("join_cross", lambda s, d: T(s, d, "region").select("r_name").crossJoin(T(s, d, "nation").select("n_name")), "SELECT r_name, n_name FROM region, nation")
    add("join_nlj", lambda s, d: T(s, d, "nation").join(T(s, d, "region"), F.col("n_nationkey") < F.col("r_regionkey")).select("n_name", "r_name"), "SELECT n_name, r_name FROM nation JOIN region ON n_nationkey < r_regionkey")
    bands = lambda s: s.range(0, 40).select(F.col("id").alias("band"), (F.col("id") * 250.0 - 1000).alias("low"), (F.col("id") * 250.0 - 600).alias("high"))
    add("join_range", lambda s, d: relops.range_join(T(s, d, "customer").select("c_custkey", "c_acctbal").withColumn("k", F.lit(1)), bands(s).withColumn("k", F.lit(1)), ["k"], "c_acctbal", "low", "high", 400.0).select("c_custkey", "band"), "SELECT c_custkey, band FROM customer JOIN (SELECT range AS band, range * 250.0 - 1000 AS low, range * 250.0 - 600 AS high FROM range(40)) ON c_acctbal >= low AND c_acctbal < high")
    purchases = lambda s, d: T(s, d, "events").select("event_id", F.col("user_id").alias("u"), F.col("ts").cast("timestamp").alias("ts"), "event_type")
    views = lambda s, d: purchases(s, d).where("event_type = 'view'").select("u", F.unix_micros("ts").alias("lo"), (F.unix_micros("ts") + 3_600_000_000).alias("hi"), F.col("event_id").alias("view"))
    add("join_interval", lambda s, d: relops.range_join(purchases(s, d).where("event_type = 'purchase'").withColumn("at", F.unix_micros("ts")), views(s, d), ["u"], "at", "lo", "hi", 3_600_000_000.0).select("event_id", "view"), "SELECT a.event_id, b.event_id AS \"view\" FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'view' AND a.ts >= b.ts AND a.ts < b.ts + INTERVAL 1 HOUR")
    add("join_asof", lambda s, d: relops.asof_join(purchases(s, d).where("event_type = 'click'").select("event_id", "u", "ts"), T(s, d, "orders").select(F.col("o_custkey").alias("u"), "o_orderdate", "o_orderkey"), "u", "ts", "o_orderdate", "o_orderkey").select("event_id", F.col("last_o_orderkey").alias("order_key")), "SELECT event_id, (SELECT max(o_orderkey) FROM orders WHERE o_custkey = user_id AND o_orderdate = (SELECT max(o_orderdate) FROM orders WHERE o_custkey = user_id AND o_orderdate <= ts)) AS order_key FROM events WHERE event_type = 'click'")
    add("join_nullsafe", lambda s, d: T(s, d, "nation").select(F.when(F.col("n_regionkey") > 0, F.col("n_regionkey")).alias("k"), "n_name").alias("a").join(T(s, d, "region").select(F.when(F.col("r_regionkey") > 0, F.col("r_regionkey")).alias("k2"), "r_name"), F.col("k").eqNullSafe(F.col("k2"))).select("n_name", "r_name"), "SELECT n_name, r_name FROM nation JOIN region ON nullif(n_regionkey, 0) IS NOT DISTINCT FROM nullif(r_regionkey, 0)")
    add("join_self", lambda s, d: T(s, d, "nation").alias("a").join(T(s, d, "nation").alias("b"), F.expr("a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("x"), F.col("b.n_name").alias("y")), "SELECT a.n_name AS x, b.n_name AS y FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
    lines = lambda s, d: T(s, d, "lineitem").select("l_returnflag", "l_linenumber", "l_orderkey")
    add("join_skew", lambda s, d: relops.skew_join(lines(s, d), lines(s, d).groupBy("l_returnflag").agg(F.max("l_orderkey").alias("top")), "l_returnflag", relops.hot_keys(lines(s, d), "l_returnflag", 0.05)).select("l_orderkey", "l_returnflag", "top"), "SELECT l_orderkey, l_returnflag, top FROM lineitem JOIN (SELECT l_returnflag, max(l_orderkey) AS top FROM lineitem GROUP BY 1) USING (l_returnflag)")
    # ---- aggregates
    g = lambda s, d: graph(s, d, "shop")
    one_ = "*"
    add("agg_count_p", lambda s, d: g(s, d).groupBy("p").agg(F.count(one_).alias("n")), "SELECT p, count(*) AS n FROM g GROUP BY p")
    add("agg_distinct_so", lambda s, d: g(s, d).groupBy("p").agg(F.countDistinct("s").alias("n_s"), F.countDistinct("o").alias("n_o")), "SELECT p, count(DISTINCT s) AS n_s, count(DISTINCT o) AS n_o FROM g GROUP BY p")
    from triplefed.stats import degrees, star_degrees

    def degree(s: SparkSession, d: str, ends: str = "so") -> DataFrame:
        """v, degree as ends of triples: by the graph's subjects where that is known to be right, else from the triples."""
        found = stars(s, d)
        if found is not None:
            return star_degrees(found, ends)
        return degrees(g(s, d)) if ends == "so" else g(s, d).groupBy(F.col(ends).alias("v")).agg(F.count(one_).alias("degree"))

    add("agg_degree_in", lambda s, d: degree(s, d, "o").withColumnRenamed("degree", "n"), "SELECT o AS v, count(*) AS n FROM g GROUP BY o")
    add("agg_degree_out", lambda s, d: degree(s, d, "s").withColumnRenamed("degree", "n"), "SELECT s AS v, count(*) AS n FROM g GROUP BY s")
    add("agg_degree_total", lambda s, d: degree(s, d), "SELECT v, count(*) AS degree FROM (SELECT s AS v FROM g UNION ALL SELECT o FROM g) GROUP BY v")
    r = lambda c, n: F.round(c, 4).alias(n)
    add("agg_avg_std", lambda s, d: T(s, d, "customer").groupBy("c_nationkey").agg(r(F.avg("c_acctbal"), "mean"), r(F.stddev_pop("c_acctbal"), "sd"), F.min("c_acctbal").alias("low"), F.max("c_acctbal").alias("high")), "SELECT c_nationkey, round(avg(c_acctbal), 4) AS mean, round(stddev_pop(c_acctbal), 4) AS sd, min(c_acctbal) AS low, max(c_acctbal) AS high FROM customer GROUP BY 1")
    add("agg_sum", lambda s, d: T(s, d, "lineitem").groupBy("l_suppkey").agg(F.sum(F.col("l_quantity").cast("long")).alias("quantity")), "SELECT l_suppkey, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity FROM lineitem GROUP BY 1")
    add("agg_mode", lambda s, d: relops.top_k_per(T(s, d, "events").groupBy("user_id", "event_type").agg(F.count(one_).alias("n")), "user_id", [F.col("n").desc(), "event_type"], 1).select("user_id", "event_type"), "SELECT user_id, first(event_type ORDER BY n DESC, event_type) AS event_type FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY 1")
    add("agg_pctl", lambda s, d: T(s, d, "part").groupBy("p_brand").agg(F.percentile("p_size", 0.5).alias("median")), "SELECT p_brand, quantile_cont(CAST(p_size AS DOUBLE), 0.5) AS median FROM part GROUP BY 1")
    add("agg_maxby", lambda s, d: T(s, d, "orders").groupBy("o_custkey").agg(F.max(F.struct("o_totalprice", "o_orderkey")).alias("x")).select("o_custkey", F.col("x.o_orderkey").alias("largest")), "SELECT o_custkey, first(o_orderkey ORDER BY o_totalprice DESC, o_orderkey DESC) AS largest FROM orders GROUP BY 1")
    add("agg_collect", lambda s, d: T(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_set("n_name")), ",").alias("names")), "SELECT n_regionkey, string_agg(DISTINCT n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
    add("agg_having", lambda s, d: T(s, d, "orders").groupBy("o_custkey").agg(F.count(one_).alias("n")).where("n > 5"), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 5")
    add("agg_filter", lambda s, d: T(s, d, "lineitem").groupBy("l_suppkey").agg(F.count_if(F.col("l_returnflag") == "R").alias("returned"), F.count(one_).alias("n")), "SELECT l_suppkey, count(*) FILTER (l_returnflag = 'R') AS returned, count(*) AS n FROM lineitem GROUP BY 1")
    pw = lambda s, d: place(g(s, d).drop("home"), "hash_s").select("p", "home")
    from triplefed.federation import worker_sql

    homes = f"(SELECT p, {worker_sql('s', WORKERS)} AS home FROM g)"
    add("agg_rollup", lambda s, d: pw(s, d).rollup("p", "home").agg(F.count(one_).alias("n")).select("p", F.coalesce("home", F.lit(-1)).alias("home"), "n"), f"SELECT p, coalesce(home, -1) AS home, count(*) AS n FROM {homes} GROUP BY ROLLUP (p, home)")
    add("agg_cube", lambda s, d: pw(s, d).cube("p", "home").agg(F.count(one_).alias("n")).select("p", F.coalesce("home", F.lit(-1)).alias("home"), "n"), f"SELECT p, coalesce(home, -1) AS home, count(*) AS n FROM {homes} GROUP BY CUBE (p, home)")
    add("agg_gsets", lambda s, d: pw(s, d).groupingSets([["p"], ["home"]], "p", "home").agg(F.count(one_).alias("n")).select("p", F.coalesce("home", F.lit(-1)).alias("home"), "n"), f"SELECT p, coalesce(home, -1) AS home, count(*) AS n FROM {homes} GROUP BY GROUPING SETS ((p), (home))")
    add("agg_pivot", lambda s, d: T(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))), "SELECT o_orderpriority, nullif(count(*) FILTER (o_orderstatus = 'F'), 0) AS F, nullif(count(*) FILTER (o_orderstatus = 'O'), 0) AS O, nullif(count(*) FILTER (o_orderstatus = 'P'), 0) AS P FROM orders GROUP BY 1")
    add("agg_approx", lambda s, d: g(s, d).groupBy("p").agg(F.approx_count_distinct("s", 0.02).alias("n_s"), F.approx_count_distinct("o", 0.02).alias("n_o")))
    # a text has no hash buffer, so Spark sorts for a first value; the order inside makes it the same in any plan
    add("agg_sort", lambda s, d: T(s, d, "orders").groupBy("o_orderstatus").agg(F.min("o_orderpriority").alias("first_priority"), F.count(one_).alias("n")), "SELECT o_orderstatus, min(o_orderpriority) AS first_priority, count(*) AS n FROM orders GROUP BY 1")
    # ---- windows
    deg = lambda s, d: g(s, d).groupBy("p", "o").agg(F.count(one_).alias("n")).where("p IN ('custNation', 'suppNation', 'brand')")
    by = lambda: Window.partitionBy("p").orderBy(F.col("n").desc(), "o")
    peers = lambda: Window.partitionBy("p").orderBy(F.col("n").desc())
    degs = "(SELECT p, o, count(*) AS n FROM (" + edge_union(("custNation", "suppNation", "brand")) + ") GROUP BY ALL)"
    wd, pr = "OVER (PARTITION BY p ORDER BY n DESC, o)", "OVER (PARTITION BY p ORDER BY n DESC)"
    add("win_rank", lambda s, d: deg(s, d).select("p", "o", F.row_number().over(by()).cast("long").alias("rn"), F.rank().over(peers()).cast("long").alias("rk"), F.dense_rank().over(peers()).cast("long").alias("dr"), F.ntile(4).over(by()).cast("long").alias("nt"), r(F.percent_rank().over(peers()), "pr"), r(F.cume_dist().over(peers()), "cd")), f"SELECT p, o, row_number() {wd} AS rn, rank() {pr} AS rk, dense_rank() {pr} AS dr, ntile(4) {wd} AS nt, round(percent_rank() {pr}, 4) AS pr, round(cume_dist() {pr}, 4) AS cd FROM {degs}")
    log = lambda s, d: w.query_log(T(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")))
    seq = lambda: Window.partitionBy("template_id").orderBy("seq")
    wl = "OVER (PARTITION BY event_type ORDER BY event_id)"
    add("win_lag", lambda s, d: log(s, d).select("seq", F.lag("seq", 1, -1).over(seq()).alias("before"), F.lead("seq", 1, -1).over(seq()).alias("after")), f"SELECT event_id AS seq, lag(event_id, 1, -1) {wl} AS before, lead(event_id, 1, -1) {wl} AS after FROM events")
    whole = lambda: seq().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    wa = "OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
    add("win_first", lambda s, d: log(s, d).select("seq", F.first("seq").over(whole()).alias("first"), F.last("seq").over(whole()).alias("last")), f"SELECT event_id AS seq, first(event_id) {wa} AS first, last(event_id) {wa} AS last FROM events")
    add("win_cum", lambda s, d: log(s, d).select("seq", F.count(one_).over(seq()).alias("cum")), f"SELECT event_id AS seq, count(*) {wl} AS cum FROM events")
    add("win_mov", lambda s, d: log(s, d).select("seq", F.sum(F.col("seq")).over(seq().rowsBetween(-2, 0)).alias("last3")), "SELECT event_id AS seq, CAST(sum(event_id) OVER (PARTITION BY event_type ORDER BY event_id ROWS 2 PRECEDING) AS BIGINT) AS last3 FROM events")
    add("win_range", lambda s, d: log(s, d).withColumn("t", F.unix_micros("ts")).select("seq", F.count(one_).over(Window.partitionBy("template_id").orderBy("t").rangeBetween(-3_600_000_000, 0)).alias("hour")), "SELECT event_id AS seq, count(*) OVER (PARTITION BY event_type ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS hour FROM events")
    add("top_k", lambda s, d: degree(s, d).orderBy(F.col("degree").desc(), "v").limit(10), "SELECT v, count(*) AS degree FROM (SELECT s AS v FROM g UNION ALL SELECT o FROM g) GROUP BY v ORDER BY 2 DESC, 1 LIMIT 10")
    add("top_k_per_p", lambda s, d: relops.top_k_per(deg(s, d), "p", [F.col("n").desc(), "o"], 3).select("p", "o", "n"), f"SELECT p, o, n FROM (SELECT *, row_number() {wd} AS k FROM {degs}) WHERE k <= 3")
    add("top_offset", lambda s, d: T(s, d, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").offset(5).limit(10).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
    add("sort_total", lambda s, d: T(s, d, "supplier").orderBy(F.col("s_acctbal").desc(), "s_suppkey").select("s_suppkey", "s_acctbal"), "SELECT s_suppkey, s_acctbal FROM supplier ORDER BY 2 DESC, 1")
    # ---- sets
    a = lambda s, d: T(s, d, "customer").select(F.col("c_nationkey").alias("n"))
    b = lambda s, d: T(s, d, "supplier").select(F.col("s_nationkey").alias("n"))
    qa, qb = "SELECT c_nationkey AS n FROM customer", "SELECT s_nationkey AS n FROM supplier"
    for name, f, word in (("union_all", lambda x, y: x.unionAll(y), "UNION ALL"), ("union", lambda x, y: x.union(y).distinct(), "UNION"), ("intersect", lambda x, y: x.intersect(y), "INTERSECT"), ("intersect_all", lambda x, y: x.intersectAll(y), "INTERSECT ALL"), ("except", lambda x, y: x.subtract(y), "EXCEPT"), ("except_all", lambda x, y: x.exceptAll(y), "EXCEPT ALL")):
        add(f"set_{name}", lambda s, d, f=f: f(a(s, d), b(s, d)), f"{qa} {word} {qb}")
    # ---- functions
    same = {
        "fn_str": ("part", "p_partkey, concat(p_brand, '-', p_type) AS joined, substring(p_name, 2, 3) AS part, replace(p_brand, '#', ':') AS swapped, lower(p_type) AS low, length(p_name) AS n, md5(p_name) AS digest, trim(concat('  ', p_type, ' ')) AS bare"),
        "fn_date": ("orders", "o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS dd"),
        "fn_math": ("customer", "c_custkey, abs(c_acctbal) AS a, round(sqrt(abs(c_acctbal)), 4) AS r, floor(c_acctbal) AS f, round(ln(abs(c_acctbal) + 1), 4) AS l, c_custkey % 7 AS m, round(power(c_nationkey, 2), 2) AS p"),
        "fn_cond": ("customer", "c_custkey, CASE WHEN c_acctbal < 0 THEN 'owes' WHEN c_acctbal < 1000 THEN 'some' ELSE 'more' END AS band, coalesce(nullif(c_nationkey, 3), -1) AS n"),
    }
    for name, (t, columns) in same.items():
        cast = columns.replace("floor(c_acctbal) AS f", "CAST(floor(c_acctbal) AS BIGINT) AS f")
        add(name, lambda s, d, t=t, x=cast: T(s, d, t).selectExpr(*_split(x)), f"SELECT {cast} FROM {t}")
    add("fn_date_trunc", lambda s, d: T(s, d, "events").select("event_id", F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH:mm").alias("hour"), F.unix_seconds(F.col("ts").cast("timestamp")).alias("epoch"), F.date_format(F.date_add(F.to_date("ts"), 3), "yyyy-MM-dd").alias("later")), "SELECT event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS hour, CAST(floor(epoch_us(ts) / 1000000) AS BIGINT) AS epoch, strftime(CAST(ts AS DATE) + 3, '%Y-%m-%d') AS later FROM events")
    v = lambda: F.col("embedding").cast("array<double>")
    add("fn_arr", lambda s, d: T(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), r(F.aggregate(F.transform(v(), lambda x: x * x), F.lit(0.0), lambda p, x: p + x), "norm2"), F.size(F.filter(v(), lambda x: x > 0)).alias("positive")), "SELECT vec_id, CAST(len(embedding) AS INT) AS n, round(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)), 4) AS norm2, CAST(len(list_filter(embedding::DOUBLE[], lambda x: x > 0)) AS INT) AS positive FROM embeddings")
    add("fn_explode", lambda s, d: T(s, d, "benchmark").select("item_id", F.posexplode(F.slice(F.split("text", " "), 1, 3)).alias("i", "word")), "SELECT item_id, CAST(i AS INT) AS i, words[i + 1] AS word FROM (SELECT item_id, string_split(text, ' ')[1:3] AS words, unnest(range(least(3, len(string_split(text, ' '))))) AS i FROM benchmark)")
    add("fn_map", lambda s, d: T(s, d, "orders").groupBy("o_custkey", "o_orderstatus").agg(F.count(one_).alias("n")).groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m")).select("o_custkey", F.size(F.map_keys("m")).alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("F")), F.lit(0)).alias("f")), "SELECT o_custkey, CAST(count(DISTINCT o_orderstatus) AS INT) AS kinds, count(*) FILTER (o_orderstatus = 'F') AS f FROM orders GROUP BY 1")
    add("fn_json", lambda s, d: T(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("k2")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, CAST(json_extract_string(props, '$.k') AS INT) AS k2 FROM events")
    add("fn_decimal", lambda s, d: T(s, d, "orders").select("o_orderkey", F.col("o_totalprice").cast("decimal(18,2)").cast("string").alias("price")), "SELECT o_orderkey, CAST(CAST(o_totalprice AS DECIMAL(18,2)) AS VARCHAR) AS price FROM orders")
    add("fn_struct", lambda s, d: T(s, d, "nation").select(F.struct("n_name", "n_regionkey").alias("x")).select(F.col("x.n_name").alias("name"), F.col("x.n_regionkey").alias("region")), "SELECT n_name AS name, n_regionkey AS region FROM nation")
    add("fn_regex_all", lambda s, d: T(s, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit("<p>"), F.lit(0))).alias("n")), "SELECT page_id, CAST(len(regexp_extract_all(html, '<p>')) AS INT) AS n FROM pages")
    # ---- iteration
    start = lambda s: s.createDataFrame([("supplier/3",)], "v string")
    hops = "WITH RECURSIVE r(v, hop) AS (SELECT 'supplier/3', 0 UNION SELECT g.o, hop + 1 FROM r JOIN g ON g.s = r.v WHERE hop < {0}) SELECT v, CAST(min(hop) AS INT) AS hop FROM r GROUP BY v"
    for k in (2, 4):
        add(f"iter_khop_{k}", lambda s, d, k=k: relops.reachable(g(s, d), start(s), k), hops.format(k))
    # to wherever it leads: no edge of this graph leads back, and no path is longer than the predicates
    add("iter_reach", lambda s, d: relops.reachable(g(s, d), start(s), 20), hops.format(20))
    # ---- streams, drained
    add("str_log", lambda s, d: streams.drain(streams.read_log(s, d)).select("seq", "template_id"), "SELECT event_id AS seq, event_type AS template_id FROM events")
    iso = lambda df: df.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "template_id", "n")
    add("str_tumble", lambda s, d: iso(streams.drain(streams.frequency(streams.read_log(s, d)), "complete")), "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type AS template_id, count(*) AS n FROM events GROUP BY ALL")
    add("str_slide", lambda s, d: iso(streams.drain(streams.frequency(streams.read_log(s, d), "1 day", "12 hours"), "complete")), "SELECT strftime(b - INTERVAL (k * 12) HOUR, '%Y-%m-%d %H:%M:%S') AS start, event_type AS template_id, count(*) AS n FROM (SELECT event_type, time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') AS b FROM events), (SELECT unnest([0, 1]) AS k) GROUP BY ALL")
    add("str_session", lambda s, d: iso(streams.drain(streams.sessions(streams.read_log(s, d)), "complete")), "SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, template_id, count(*) AS n FROM (SELECT ts, template_id, sum(fresh) OVER (PARTITION BY template_id ORDER BY ts, event_id) AS k FROM (SELECT event_id, ts, event_type AS template_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY event_type ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY template_id, k")
    add("str_trigger", lambda s, d: streams.drain(streams.triggers(streams.read_log(s, d))), "SELECT event_type AS template_id, CAST(3 AS INT) AS freq FROM events GROUP BY 1 HAVING count(*) > 3")
    add("str_dedup", lambda s, d: streams.drain(streams.deduplicated(streams.read_log(s, d))).select("seq"), "SELECT DISTINCT event_id AS seq FROM events")
    add("str_late", lambda s, d: streams.late_rows(s, d).select("window_start", "n"), streams.LATE_SQL)
    add("str_updates", lambda s, d: streams.updated_graph(s, d), "SELECT p, count(*) AS n FROM (" + edge_union(("brand", "partKind")) + f") WHERE ('0x' || substr(md5(concat(s, '|', p, '|', o)), 1, 8))::BIGINT % 5 <> 0 OR p = 'brand' GROUP BY p")
    add("str_static", lambda s, d: streams.drain(streams.with_graph(streams.read_log(s, d), g(s, d), "custNation")), f"SELECT event_id AS seq, concat('customer/', user_id) AS who, n AS value FROM events JOIN {_e('custNation', 'c', 'n')} ON c = concat('customer/', user_id)")
    add("str_ssjoin", lambda s, d: streams.drain(streams.within(streams.read_log(s, d), streams.read_log(s, d))), "SELECT a.event_id AS seq_a, b.event_id AS seq_b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTE")
    # ---- user functions
    rows = [(n, " . ".join(" ".join(e) for e in x.patterns)) for n, x in w.QUERIES.items()]
    add("udf_canonical", lambda s, d: _shipped(s).createDataFrame(rows, "qid string, text string").select("qid", udfs.canonical_text()("text").alias("canonical")), "SELECT * FROM (VALUES " + ", ".join(f"('{n}', '{_canonical(n)}')" for n in w.QUERIES) + ") AS x(qid, canonical)")
    add("udtf_ntriples", lambda s, d: udfs.parse_lines(_shipped(s), LINES), "SELECT * FROM (VALUES " + ", ".join(f"({i}, '{a}', '{b}', '{c}')" for i, a, b, c in PARSED) + ") AS x(line, s, p, o)")
    add("udtf_expand", lambda s, d: udfs.expand_table(s, s.createDataFrame(rows, "qid string, text string")), "SELECT * FROM (VALUES " + ", ".join(f"('{n}', CAST({i} AS INT), '{e.s}', '{e.p}', '{e.o}')" for n, x in w.QUERIES.items() for i, e in enumerate(x.patterns)) + ") AS x(qid, place, s, p, o)")
    add("udaf_gini", lambda s, d: g(s, d).groupBy("p", "home").agg(F.count(one_).alias("load")).groupBy("p").agg(F.round(udfs.gini_udaf()("load"), 6).alias("gini")), f"SELECT p, round(CAST(sum((2 * i - n - 1) * load) AS DOUBLE) / (max(n) * sum(load)), 6) AS gini FROM (SELECT p, load, row_number() OVER (PARTITION BY p ORDER BY load) AS i, count(*) OVER (PARTITION BY p) AS n FROM (SELECT p, home, count(*) AS load FROM (SELECT p, {_home()} AS home FROM g) GROUP BY ALL)) GROUP BY p")
    local = lambda s, d, p: place(g(s, d).drop("home").where(F.col("p") == p), "hash_s" if p == "custNation" else "hash_o")
    add("udf_worker_local", lambda s, d: udfs.worker_local_join(local(s, d, "placedBy").select(F.col("home").alias("worker"), F.col("s").alias("src"), F.col("o").alias("prop")), local(s, d, "custNation").select(F.col("home").alias("worker"), F.col("s").alias("src"), F.col("o").alias("prop"))), f"SELECT {worker_sql('c', WORKERS)} AS worker, o AS root, c AS middle, n AS leaf FROM {_e('placedBy', 'o', 'c')} JOIN {_e('custNation', 'c', 'n')} USING (c)")
    # ---- SPARQL
    sparql = {
        "bgp": ("SELECT ?o ?n WHERE { ?o placedBy ?c . ?c custNation ?n ; segment seg/BUILDING }", f"SELECT o, n FROM {_e('placedBy', 'o', 'c')} JOIN {_e('custNation', 'c', 'n')} USING (c) JOIN {_e('segment', 'c', 'g')} USING (c) WHERE g = 'seg/BUILDING'"),
        "prefix_distinct": ("PREFIX n: <nation/> SELECT DISTINCT ?g WHERE { ?c custNation n:3 . ?c segment ?g }", f"SELECT DISTINCT g FROM {_e('custNation', 'c', 'n')} JOIN {_e('segment', 'c', 'g')} USING (c) WHERE n = 'nation/3'"),
        "filter": ("SELECT ?p ?z WHERE { ?p partSize ?z . FILTER(?z >= 10 && !(?z > 20)) }", f"SELECT p, z FROM {_e('partSize', 'p', 'z')} WHERE CAST(substr(z, 6) AS INT) BETWEEN 10 AND 20"),
        "regex": ("SELECT ?p ?b WHERE { ?p brand ?b . FILTER(REGEX(?b, \"#1\")) }", f"SELECT p, b FROM {_e('brand', 'p', 'b')} WHERE contains(b, '#1')"),
        "optional": ("SELECT ?c ?o WHERE { ?c custNation nation/3 . OPTIONAL { ?o placedBy ?c } }", f"SELECT c, o FROM (SELECT c FROM {_e('custNation', 'c', 'n')} WHERE n = 'nation/3') LEFT JOIN {_e('placedBy', 'o', 'c')} USING (c)"),
        "union": ("SELECT ?x WHERE { { ?x custNation nation/3 } UNION { ?x suppNation nation/3 } }", f"SELECT c AS x FROM {_e('custNation', 'c', 'n')} WHERE n = 'nation/3' UNION ALL SELECT s AS x FROM {_e('suppNation', 's', 'n')} WHERE n = 'nation/3'"),
        "minus": ("SELECT ?c WHERE { ?c custNation nation/3 . MINUS { ?o placedBy ?c } }", f"SELECT c FROM {_e('custNation', 'c', 'n')} WHERE n = 'nation/3' AND c NOT IN (SELECT c FROM {_e('placedBy', 'o', 'c')})"),
        "notexists": ("SELECT ?c WHERE { ?c custNation nation/3 . FILTER NOT EXISTS { ?e byUser ?c } }", f"SELECT c FROM {_e('custNation', 'c', 'n')} WHERE n = 'nation/3' AND c NOT IN (SELECT c FROM {_e('byUser', 'e', 'c')})"),
        "group": ("SELECT ?n (COUNT(DISTINCT ?c) AS ?k) (AVG(?z) AS ?m) WHERE { ?c custNation ?n . ?e byUser ?c . ?e eventKind ekind/view . ?o placedBy ?c . ?o orderYear ?z } GROUP BY ?n", f"SELECT n, count(DISTINCT c) AS k, sum(CAST(substr(z, 6) AS DOUBLE)) / count(*) AS m FROM {_e('custNation', 'c', 'n')} JOIN {_e('byUser', 'e', 'c')} USING (c) JOIN {_e('eventKind', 'e', 'q')} USING (e) JOIN {_e('placedBy', 'o', 'c')} USING (c) JOIN {_e('orderYear', 'o', 'z')} USING (o) WHERE q = 'ekind/view' GROUP BY n"),
        "order_limit": ("SELECT ?s ?n WHERE { ?s suppNation ?n } ORDER BY DESC(?n) ?s LIMIT 7 OFFSET 2", f"SELECT s, n FROM {_e('suppNation', 's', 'n')} ORDER BY n DESC, s LIMIT 7 OFFSET 2"),
        "ask": ("ASK { ?s suppNation nation/3 }", f"SELECT count(*) > 0 AS found FROM {_e('suppNation', 's', 'n')} WHERE n = 'nation/3'"),
        "predicate": ("SELECT ?p ?o WHERE { customer/7 ?p ?o }", "SELECT p, o FROM g WHERE s = 'customer/7'"),
    }
    for name, (text, oracle) in sparql.items():
        add(f"sparql_{name}", lambda s, d, x=text: parse_sparql(x).run(g(s, d)), oracle)
    for name, members in FOLDS.items():
        names = members.split()
        q[name] = lambda s, d, names=names: reduce(DataFrame.unionByName, [_digest(n, one[n][0](s, d)) for n in names])
        o[name] = _with_graph(shop, " UNION ALL ".join(_digest_sql(n, one[n][1]) for n in names))
    return q, o


#: Lines of triples as text, and what they say.
LINES = ['<a> <p> <b> .', '<a> <q> "some text" .', 'nothing', '# remark', '<c> <p> <a> .']
PARSED = ((0, "a", "p", "b"), (1, "a", "q", "some text"), (4, "c", "p", "a"))


def edge_union(names: tuple[str, ...]) -> str:
    return " UNION ALL ".join(f"SELECT s, '{p}' AS p, o FROM ({edge_sql('shop', p)})" for p in names)


def _with_graph(shop: str, body: str) -> str:
    """With all triples as g, where the body reads them."""
    return sqlgen.with_graph(shop, body) if re.search(r"\b(FROM|JOIN) g\b", body) else body


def _split(columns: str) -> list[str]:
    """At commas outside brackets."""
    out, depth, part = [], 0, ""
    for ch in columns:
        depth += (ch == "(") - (ch == ")")
        if ch == "," and not depth:
            out.append(part)
            part = ""
        else:
            part += ch
    return [*out, part]


def _canonical(name: str) -> str:
    from triplefed.query import canonical

    return canonical(w.QUERIES[name])[0]


def _shipped(spark: SparkSession) -> SparkSession:
    udfs.ship(spark)
    return spark


def _home() -> str:
    from triplefed.federation import place_sql

    return place_sql("random")
