"""The given tables as sets of triples.

A graph is a union of one projection for each predicate, with the predicate as a constant: a selection on ``p`` prunes
the union to the tables that carry it, and column pruning reaches their scans. Only branches whose rows can repeat are
made distinct, so a scan of the others costs no shuffle. The same branches are kept as SQL text, which other engines run.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.storage import tidy

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

_LINE = "concat('line/', l_orderkey, '-', l_linenumber, '-', l_partkey, '-', l_suppkey)"

#: predicate, table, subject, object, whether rows can repeat; expressions that Spark SQL and DuckDB read alike
SHOP = (
    ("type", "region", "concat('region/', r_regionkey)", "'class/region'", False),
    ("type", "nation", "concat('nation/', n_nationkey)", "'class/nation'", False),
    ("type", "customer", "concat('customer/', c_custkey)", "'class/customer'", False),
    ("type", "supplier", "concat('supplier/', s_suppkey)", "'class/supplier'", False),
    ("type", "part", "concat('part/', p_partkey)", "'class/part'", False),
    ("type", "orders", "concat('order/', o_orderkey)", "'class/order'", False),
    ("type", "lineitem", _LINE, "'class/line'", True),
    ("type", "events", "concat('event/', event_id)", "'class/event'", False),
    ("inRegion", "nation", "concat('nation/', n_nationkey)", "concat('region/', n_regionkey)", False),
    ("custNation", "customer", "concat('customer/', c_custkey)", "concat('nation/', c_nationkey)", False),
    ("segment", "customer", "concat('customer/', c_custkey)", "concat('seg/', c_mktsegment)", False),
    ("suppNation", "supplier", "concat('supplier/', s_suppkey)", "concat('nation/', s_nationkey)", False),
    ("brand", "part", "concat('part/', p_partkey)", "concat('brand/', p_brand)", False),
    ("partKind", "part", "concat('part/', p_partkey)", "concat('kind/', p_type)", False),
    ("partSize", "part", "concat('part/', p_partkey)", "concat('size/', p_size)", False),
    ("placedBy", "orders", "concat('order/', o_orderkey)", "concat('customer/', o_custkey)", False),
    ("status", "orders", "concat('order/', o_orderkey)", "concat('status/', o_orderstatus)", False),
    ("priority", "orders", "concat('order/', o_orderkey)", "concat('prio/', o_orderpriority)", False),
    ("orderYear", "orders", "concat('order/', o_orderkey)", "concat('year/', year(o_orderdate))", False),
    ("ofOrder", "lineitem", _LINE, "concat('order/', l_orderkey)", True),
    ("ofPart", "lineitem", _LINE, "concat('part/', l_partkey)", True),
    ("soldBy", "lineitem", _LINE, "concat('supplier/', l_suppkey)", True),
    ("returnFlag", "lineitem", _LINE, "concat('flag/', l_returnflag)", True),
    ("shipYear", "lineitem", _LINE, "concat('year/', year(l_shipdate))", True),
    ("supplies", "lineitem", "concat('supplier/', l_suppkey)", "concat('part/', l_partkey)", True),
    ("byUser", "events", "concat('event/', event_id)", "concat('customer/', user_id)", False),
    ("eventKind", "events", "concat('event/', event_id)", "concat('ekind/', event_type)", False),
)

CONTENT = (
    ("lang", "documents", "concat('doc/', doc_id)", "concat('lang/', lang)", False),
    ("source", "documents", "concat('doc/', doc_id)", "concat('source/', source)", False),
    ("quality", "labels", "concat('doc/', doc_id)", "concat('quality/', quality)", False),
    ("toxic", "labels", "concat('doc/', doc_id)", "concat('toxic/', toxic)", False),
    ("onHost", "pages", "concat('page/', page_id)", "concat('host/', regexp_extract(url, '://([^/]+)', 1))", False),
    ("pageLang", "pages", "concat('page/', page_id)", "concat('plang/', regexp_extract(html, 'html lang=\"([a-z]+)\"', 1))", False),
    ("inConv", "conversations", "concat('turn/', conv_id, '-', turn)", "concat('conv/', conv_id)", False),
    ("role", "conversations", "concat('turn/', conv_id, '-', turn)", "concat('role/', role)", False),
    ("cluster", "embeddings", "concat('vec/', vec_id)", "concat('cluster/', label)", False),
)

#: Which repository holds a predicate's triples first, where each table is a repository.
_TABLE_OF = {p: t for p, t, *_ in (*SHOP, *CONTENT)}


@dataclass(frozen=True)
class Star:
    """``rows``: s, and o_<p> for each of its predicates, null where there is no such triple. ``alone``: each subject has one
    row, and no other triple has it as an end."""

    rows: DataFrame
    predicates: tuple[str, ...]
    alone: bool = False


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: What tells a line from another.
LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def lines_once(spark: SparkSession, sf_dir: str) -> bool:
    """Whether no line comes twice, by one shuffle of 8 bytes a line. Then no branch whose subject is a line can repeat, and
    reading the graph need not make them distinct. Two lines of one hash count as a line that comes twice."""
    lines = read_table(spark, sf_dir, "lineitem")
    size = int(lines._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    keys = lines.where(" AND ".join(f"{c} IS NOT NULL" for c in LINE_KEY)).select(F.xxhash64(*LINE_KEY).alias("h"))
    # parts of a few hundred thousand lines, whose hashes a task holds without spilling
    dealt = keys.repartition(max(1, min(8192, size // (4 << 20))), "h")
    with tidy(spark):
        return dealt.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty()


def _triples(spark: SparkSession, sf_dir: str, branches: tuple, names: set[str], once: bool = False) -> DataFrame:
    out = None
    for p, table, s, o, repeats in branches:
        if table not in names:
            continue
        part = read_table(spark, sf_dir, table)
        repeats = repeats and not (once and s == _LINE)
        if repeats:
            part, s, o = _different(part, s, o)
        part = part.select(F.expr(s).alias("s"), F.lit(p).alias("p"), F.expr(o).alias("o"))
        part = part if repeats else part.where("s IS NOT NULL AND o IS NOT NULL")
        out = part if out is None else out.unionByName(part)
    return out


def _different(rows: DataFrame, s: str, o: str) -> tuple[DataFrame, str, str]:
    """Each pair of terms once, and the expressions of the terms over what is left. What terms are made of is compared, not
    terms: numbers are a third as many bytes to shuffle, and predicates with the same parts share one exchange. A term says
    its parts: digits and single hyphens can be read back, and so can one text after a prefix."""
    parts = list(dict.fromkeys(x for e in (s, o) for x in _parts(e) if not x.startswith("'")))
    rows = rows.where(" AND ".join(f"{x} IS NOT NULL" for x in parts))
    kept = rows.select(*(F.expr(x).alias(f"part_{i}") for i, x in enumerate(parts))).distinct()
    over = lambda e: f"concat({', '.join(f'part_{parts.index(x)}' if x in parts else x for x in _parts(e))})"
    return kept, over(s), over(o)


def _parts(expression: str) -> list[str]:
    """What a concatenation is made of; of a literal, itself."""
    return expression[len("concat("):-1].split(", ") if expression.startswith("concat(") else [expression]


def shop_graph(spark: SparkSession, sf_dir: str, once: bool = False) -> DataFrame:
    """s, p, o of orders, lines, customers, suppliers, parts, places and events. ``once``: no line comes twice, as
    ``lines_once`` has found."""
    return _triples(spark, sf_dir, SHOP, set(TABLES), once)


def shop_stars(spark: SparkSession, sf_dir: str) -> list[Star]:
    """The shop graph by its subjects, where ``lines_once`` holds: a scan for each table instead of one for each predicate."""
    kind = lambda e: e.split("'")[1]
    ends = {kind(x[3]) for x in SHOP} | {kind(s) for s in {x[2] for x in SHOP} - {_LINE}}
    out = []
    for table, s, repeats in dict.fromkeys((x[1], x[2], x[4] and x[2] != _LINE) for x in SHOP):
        of = [x for x in SHOP if x[1:3] == (table, s)]
        rows = read_table(spark, sf_dir, table)
        subject, objects = s, [x[3] for x in of]
        if repeats:
            rows, subject, objects[0] = _different(rows, s, objects[0])
        edges = {x[0]: F.expr(o) for x, o in zip(of, objects, strict=True)}
        alone = s == _LINE and kind(s) not in ends
        rows = rows.select(F.expr(subject).alias("s"), *(o.alias(f"o_{p}") for p, o in edges.items())).where("s IS NOT NULL")
        out.append(Star(rows, tuple(edges), alone))
    return out


def content_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """s, p, o of documents, pages, conversations and vectors; few type edges, as in collections from many hands."""
    out = _triples(spark, sf_dir, CONTENT, set(TABLES))
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    # equal texts: each document points to the next larger id of its text, found by one shuffle on the text's digest
    same = docs.select("doc_id", F.md5("text").alias("h")).where("h IS NOT NULL")
    least = same.groupBy("h").agg(F.min("doc_id").alias("first"))
    same = same.join(least, "h").where("doc_id > first").select(_id("doc", "first").alias("s"), F.lit("sameText").alias("p"), _id("doc", "doc_id").alias("o"))
    # quotes: items whose first eight words occur in a document meet it by those words' hash, then the text is checked
    turns = read_table(spark, sf_dir, "conversations").select("conv_id", "turn")
    after = turns.select("conv_id", (F.col("turn") + 1).alias("turn"), F.col("turn").alias("before"))
    follows = turns.join(after, ["conv_id", "turn"]).select(F.concat(F.lit("turn/"), "conv_id", F.lit("-"), "turn").alias("s"), F.lit("follows").alias("p"), F.concat(F.lit("turn/"), "conv_id", F.lit("-"), "before").alias("o"))
    links = read_table(spark, sf_dir, "pages").select(_id("page", "page_id").alias("s"), F.lit("linksTo").alias("p"), F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).alias("href"))
    links = links.select("s", "p", F.concat(F.lit("href/"), "href").alias("o"))
    return out.unionByName(same).unionByName(quotes(spark, sf_dir)).unionByName(follows).unionByName(links)


def _id(kind: str, column: str) -> Column:
    return F.concat(F.lit(f"{kind}/"), F.col(column).cast("string"))


def quotes(spark: SparkSession, sf_dir: str, words: int = 4) -> DataFrame:
    """doc quotes item, where the document contains the item's text. Both sides are cut at blanks; runs of a few words
    are what they are joined on, so no pair is looked at that shares none."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    items = read_table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("item"))
    # the second word on: the first may be glued to what stands before it in the document
    items = items.withColumn("key", F.xxhash64(F.slice(F.split("item", r"\s+"), 2, words)))
    runs = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("w") - words + 1)), lambda i: F.xxhash64(F.slice("w", i, words)))
    keyed = docs.select("doc_id", F.split("text", r"\s+").alias("w")).select("doc_id", F.explode(F.array_distinct(runs)).alias("key"))
    found = keyed.join(items, "key").select("doc_id", "item_id", "item").distinct()
    return found.join(docs, "doc_id").where(F.contains("text", "item")).select(_id("doc", "doc_id").alias("s"), F.lit("quotes").alias("p"), _id("item", "item_id").alias("o")).distinct()


#: Branches of the content graph that are more than a projection, as SELECTs of s and o.
_DERIVED_SQL = {
    "sameText": "SELECT concat('doc/', f) AS s, concat('doc/', doc_id) AS o FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY md5(text)) AS f FROM documents WHERE text IS NOT NULL) WHERE doc_id > f",
    "quotes": "SELECT DISTINCT concat('doc/', doc_id) AS s, concat('item/', item_id) AS o FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "follows": "SELECT concat('turn/', conv_id, '-', turn) AS s, concat('turn/', conv_id, '-', before) AS o FROM (SELECT conv_id, turn FROM conversations) JOIN (SELECT conv_id, turn + 1 AS turn, turn AS before FROM conversations) USING (conv_id, turn)",
    "linksTo": "SELECT DISTINCT concat('page/', page_id) AS s, concat('href/', unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))) AS o FROM pages",
}


def predicates(name: str) -> list[str]:
    branches = SHOP if name == "shop" else CONTENT
    return list(dict.fromkeys([p for p, *_ in branches] + ([*_DERIVED_SQL] if name == "content" else [])))


def edge_sql(name: str, predicate: str, s: str | None = None, o: str | None = None) -> str:
    """s and o of one predicate's triples as a SELECT that reads only the tables that carry it, with constants applied.

    A branch whose object is another literal than the constant is left out, and so is one whose terms begin otherwise.
    """
    parts = []
    for p, table, subject, target, repeats in SHOP if name == "shop" else CONTENT:
        if p == predicate and _may_be(subject, s) and _may_be(target, o):
            parts.append(f"SELECT {'DISTINCT ' if repeats else ''}{subject} AS s, {target} AS o FROM {table}")
    if name == "content" and predicate in _DERIVED_SQL:
        parts.append(_DERIVED_SQL[predicate])
    if not parts:
        parts = ["SELECT '' AS s, '' AS o WHERE false"]
    rows = " UNION ALL ".join(parts)
    where = " AND ".join(f"{c} = {quoted(x)}" for c, x in (("s", s), ("o", o)) if x is not None)
    return f"SELECT s, o FROM ({rows}) WHERE {where}" if where else rows


def quoted(term: str) -> str:
    return "'" + term.replace("'", "''") + "'"


def _may_be(expression: str, term: str | None) -> bool:
    """Whether a branch's expression, a literal or a concatenation that begins with one, can give the term."""
    first = expression.split("'")[1]
    return term is None or (term == first if expression.startswith("'") else term.startswith(first))


def graph_sql(name: str) -> str:
    """The graph as a SELECT that DuckDB runs."""
    return " UNION ALL ".join(f"SELECT s, '{p}' AS p, o FROM ({edge_sql(name, p)})" for p in predicates(name))


def table_of(predicate: str) -> str:
    return _TABLE_OF.get(predicate, "derived")
