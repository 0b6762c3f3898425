"""Distributed mode: a chain of semi-joins over triples wherever they lie.

The left rows' join keys are what travels; the candidates that match come back to the rows they join with. As a plan: the
distinct keys, a left semi join of the next pattern with them, an inner join with the left rows. The answer of a row
stays at the home of its first pattern's triple, so the answers of workers are disjoint.

A round's left rows are written before the next round reads them, once for their keys and once for the join; so no plan
names a scan more than twice, and the number of keys is known, not guessed, when it decides how they travel.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from triplefed.operators.patterns import project, scan_pattern
from triplefed.plans.order import Relation, _joined, order_patterns, pattern_relation
from triplefed.query import QueryGraph
from triplefed.stats import Stats
from triplefed.storage import discard, save, tidy

#: Keys are broadcast only up to so many, counted; beyond, both sides shuffle.
BROADCAST_KEYS = 1_000_000
#: Bits of a key filter, a fixed 2 MB however many keys there are; and what a word of it holds.
FILTER_BITS, WORD_BITS = 1 << 24, 1 << 15
STRATEGIES = ("auto", "broadcast_keys", "shuffle", "bloom", "plain")


def key_filter(keys: DataFrame, bits: int = FILTER_BITS) -> DataFrame:
    """word, held: a filter of the rows of ``keys`` as bitmaps, ``bits`` / 8 bytes at most in all."""
    at = F.pmod(F.xxhash64(*keys.columns), F.lit(bits))
    words = keys.select(F.floor(at / WORD_BITS).cast("int").alias("word"), (at % WORD_BITS).alias("bit"))
    return words.groupBy("word").agg(F.bitmap_construct_agg("bit").alias("held"))


def pass_filter(rows: DataFrame, on: list[str], held: DataFrame, bits: int = FILTER_BITS) -> DataFrame:
    """Rows whose key may be among those of a filter; none whose key is is left out."""
    at = F.pmod(F.xxhash64(*on), F.lit(bits))
    marked = rows.withColumn("word", F.floor(at / WORD_BITS).cast("int")).withColumn("bit", (at % WORD_BITS).cast("int"))
    found = marked.join(F.broadcast(held), "word")  # as many bytes as the filter has
    byte = F.conv(F.hex(F.substring("held", F.floor(F.col("bit") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    return found.where(F.lit(1) == F.getbit(byte, (F.col("bit") % 8).cast("int"))).select(*rows.columns)


def _few(rows: DataFrame, n: int = BROADCAST_KEYS) -> bool:
    """Whether there are at most ``n``; the tasks that count pass on no more than so many each, without any column."""
    with tidy(rows.sparkSession):
        return rows.select(F.lit(1)).limit(n + 1).count() <= n


def _met(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    """``left`` joined with ``right``. Where either has few rows, counted, these are broadcast and the other stays where it is."""
    if _few(right):
        return left.join(F.broadcast(right), on)
    if _few(left):
        return left.join(right.join(F.broadcast(left.select(*on).distinct()), on, "left_semi"), on)
    return left.join(pass_filter(right, on, key_filter(left.select(*on))), on)


def _number(keys: DataFrame) -> int:
    """How many different keys. Counted by a sketch, which shuffles nothing, where they are many more than are broadcast."""
    with tidy(keys.sparkSession):
        about = keys.agg(F.approx_count_distinct(F.struct(*keys.columns))).collect()[0][0]
        return about if about > 2 * BROADCAST_KEYS else keys.distinct().count()


def _asked(right: DataFrame, left: DataFrame, on: list[str]) -> DataFrame:
    """What of ``right`` matches the keys of ``left``, which go to every worker as numbers of 8 bytes: terms as text are
    several times as much on the driver. Another key of the same number may come with them, so a join has to follow."""
    numbers = left.select(F.xxhash64(*on).alias("__key")).distinct()
    return right.withColumn("__key", F.xxhash64(*on)).join(F.broadcast(numbers), "__key", "left_semi").drop("__key")


def semi_join_step(left: DataFrame, right: DataFrame, strategy: str = "auto", keys_estimate: float | None = None, few: bool = False) -> DataFrame:
    """``left`` joined with what of ``right`` matches its keys.

    ``broadcast_keys``: every worker gets the keys. ``shuffle``: keys and candidates meet by hash. ``bloom``: every worker
    gets a filter of fixed size made of the keys; what passes meets by hash. ``auto``: the first up to a number of keys,
    the third beyond. ``plain``: no reduction. Without ``keys_estimate`` keys are counted before they are broadcast.
    ``few``: what is left of ``right`` goes to every worker, so that ``left`` stays where it is.
    """
    if strategy not in STRATEGIES:
        raise ValueError(strategy)
    on = [c for c in right.columns if c in left.columns and c != "home"]
    right = right.drop("home")
    if not on:
        return left.crossJoin(right)  # parts of a query that share no variable: their product is the answer
    if strategy == "plain":
        return left.join(right, on)
    bring = F.broadcast if few else lambda rows: rows
    if strategy == "auto" and few:
        return left.join(bring(right), on)  # as many rows as are broadcast of keys
    keys = left.select(*on).distinct()
    if strategy in ("auto", "broadcast_keys"):
        n = _number(left.select(*on)) if keys_estimate is None else keys_estimate
        if n <= BROADCAST_KEYS:
            return left.join(bring(_asked(right, left, on)), on)
        strategy = "bloom" if strategy == "auto" else "shuffle"
    if strategy == "bloom":
        return left.join(bring(pass_filter(right, on, key_filter(left.select(*on)))), on)
    return left.join(bring(right.join(keys, on, "left_semi")), on)


def run_distributed(t: DataFrame, q: QueryGraph, stats: Stats | None = None, strategy: str = "auto", keep_home: bool = False, cardinalities: list[int] | None = None, write=save) -> DataFrame:
    """With statistics, ``auto`` leaves a reduction out where the keys are as many as the next pattern has.

    What a round shuffled goes when its rows are written, and its rows when the next round's are: never are more than two
    rounds on disk. A round whose right side has few rows moves nothing and isn't written.
    """
    order = order_patterns(q, stats, cardinalities)
    out = scan_pattern(t, q.patterns[order[0]], keep_home)
    now: Relation | None = pattern_relation(q.patterns[order[0]], stats) if stats else None
    written, moved = None, False
    for e in (q.patterns[i] for i in order[1:]):
        right, how, n = scan_pattern(t, e), strategy, None
        on = [c for c in right.columns if c in out.columns and c != "home"]
        if on and strategy == "auto" and now is not None:
            part = pattern_relation(e, stats)
            if all(now.distinct.get(f"?{c}", 0) >= 0.9 * part.distinct[f"?{c}"] for c in on):
                how = "plain"
        few = bool(on) and strategy != "plain" and _few(right)
        if on and moved and not (few and how in ("auto", "plain")):
            before, out = written, write(out)
            if before is not None and write is save:
                discard(before)
            written, moved = out, False
        if how == "plain" and few:
            how = "auto"
        if on and how in ("auto", "broadcast_keys") and not (few and how == "auto"):
            n = _number(out.select(*on))
        out = semi_join_step(out, right, how, n, few)
        moved = moved or not few
        if now is not None:
            now = _joined(now, pattern_relation(e, stats))
    names = [v[1:] for v in q.variables] + (["home"] if keep_home else [])
    return out.select(*names) if keep_home else project(out, q)


def exact_cardinalities(t: DataFrame, q: QueryGraph) -> list[int]:
    """Rows of each pattern, all counted in one job."""
    parts = None
    for i, e in enumerate(q.patterns):
        one = scan_pattern(t, e).agg(F.lit(i).alias("i"), F.count(F.lit(1)).alias("n"))
        parts = one if parts is None else parts.unionByName(one)
    with tidy(t.sparkSession):
        found = {r["i"]: r["n"] for r in parts.select("*").collect()}  # a row for each pattern
    return [found[i] for i in range(len(q.patterns))]


def communication(t: DataFrame, q: QueryGraph, workers: int, stats: Stats | None = None, write=save) -> DataFrame:
    """round, keys_sent, key_bytes, candidates_sent, candidate_bytes, result_rows of each semi-join; ``t`` has ``home``.

    Keys go to all other workers; a candidate goes to each worker, other than its own, that asked for its key. Bytes are
    those of the terms as text. The last round's result rows all go to the master.

    Who asks for a key is a bit of one number a key, so a key is one row however many ask. Askers and result rows of a round
    are written before they are counted and joined; no round is computed twice.
    """
    order = order_patterns(q, stats)
    left = scan_pattern(t, q.patterns[order[0]], True)
    rounds = None
    octets = lambda names: sum((F.octet_length(c) for c in names[1:]), F.octet_length(names[0]))
    total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
    bit = lambda home: F.call_function("shiftleft", F.lit(1).cast("long"), (home % 62).cast("int"))
    for k, i in enumerate(order[1:], 1):
        right = scan_pattern(t, q.patterns[i], True)
        on = [c for c in right.columns if c in left.columns and c != "home"]
        asked = left.groupBy(*on, F.floor(F.col("home") / 62).alias("block")).agg(F.bit_or(bit(F.col("home"))).alias("askers"))
        asked = write(asked)
        n = F.bit_count("askers")
        sent = asked.agg((total(n) * (workers - 1)).alias("keys_sent"), total(octets(on) * n * (workers - 1)).alias("key_bytes"))
        terms = [c for c in right.columns if c not in ("home", "found")]
        own = (F.floor(F.col("home") / 62) == F.col("block")) & (F.col("askers").bitwiseAND(bit(F.col("home"))) != 0)
        others = n - F.coalesce(own, F.lit(False)).cast("int")
        back = _met(asked, right, on).agg(total(others).alias("candidates_sent"), total(octets(terms) * others).alias("candidate_bytes"))
        left = _met(left, right.drop("home"), on)
        if k < len(order) - 1:
            left = write(left)
        done = left.agg(F.count(F.lit(1)).alias("result_rows"))
        row = write(sent.crossJoin(back).crossJoin(done).select(F.lit(k).alias("round"), "*"))  # one row each
        rounds = row if rounds is None else rounds.unionByName(row)
    return rounds


def redistribution_traffic(t: DataFrame, modules: dict[tuple, DataFrame]) -> DataFrame:
    """module_id, moved_rows, moved_bytes: copies that leave the home of their triple for another worker. ``t`` has home;
    modules by path: worker, src, prop."""
    from triplefed.operators.cap import edge_rows, module_id

    out = None
    for path, df in modules.items():
        homes = edge_rows(t, path).select("src", "prop", "home")
        moved = df.join(homes, ["src", "prop"]).where("home <> worker")
        row = moved.agg(F.count(F.lit(1)).alias("moved_rows"), F.coalesce(F.sum(F.octet_length("src") + F.octet_length("prop")), F.lit(0)).cast("long").alias("moved_bytes")).select(F.lit(module_id(path)).alias("module_id"), "*")
        out = row if out is None else out.unionByName(row)
    return out
