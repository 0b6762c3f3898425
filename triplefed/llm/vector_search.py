"""Nearest neighbours by cosine: a vantage-point tree in each shard.

Vectors are scaled to length one, where the largest cosine is the smallest distance. A shard's tree splits its vectors
at the median distance from a vantage point, down to leaves. A block of queries goes down a tree together: first each to
its own leaf, for a first bound, then through all nodes, where a query leaves out a side if the triangle inequality,
stretched by ``factor``, says that nothing there beats its k-th nearest: side distance * factor > bound. Factor 1 is
exact; larger factors leave out more. A second pass takes all vectors within the k-th distance and ``SLACK``, so ties and
near ties come whole; they are scored anew on the original values in double precision, and the best are kept leaf by leaf.

Every vector is indexed; equal vectors take one node and their smallest ids speak for them, which loses nothing, as ties
go to smaller ids. A vector goes to one shard, of bounded size, once; the queries come to each shard after it and are
searched block by block as they arrive, as any search of a stated query set must, and only k rows of a query leave a shard.

Defined cases: vectors that are null, zero, of another length than ``length`` (most vectors have, if it isn't given), or hold
null or non-finite components take no part, neither as query nor as candidate; of repeated ids each row is a candidate,
and a query never finds rows of its own id; with fewer than k candidates all come; an empty table gives no rows; only
named columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from triplefed.llm.common import materialize, ship, table

K = 5
EVERY = 50
FACTOR = 1.0
LEAF = 128
SHARD_ROWS = 100_000
BLOCK_ROWS = 10_000
#: Distances closer than this are settled by the exact scores.
SLACK = 1e-7
#: Scored rows that a search holds before it keeps the best of them.
HELD_ROWS = 1_000_000


class Tree:
    """Nodes in arrays; ``order`` holds the rows of each leaf in a row."""

    def __init__(self, x: np.ndarray, leaf: int = LEAF):
        self.x = x
        self.order = np.arange(len(x))
        self.nodes: list[tuple] = []  # (vantage row, median, radius, inside, outside) or (None, from, to)
        self.leaf = leaf
        self.root = self._build(0, len(x))

    def _build(self, lo: int, hi: int) -> int:
        # depth is logarithmic: sides are halves
        if hi - lo <= self.leaf:
            self.nodes.append((None, lo, hi))
            return len(self.nodes) - 1
        rows = self.order[lo:hi]
        vantage = int(rows[np.argmax(_distance(self.x[rows], self.x[rows[0]]))])
        d = _distance(self.x[rows], self.x[vantage])
        mid = (hi - lo) // 2
        part = np.argpartition(d, mid)
        self.order[lo:hi] = rows[part]
        d = d[part]
        inner, outer = (float(d[:mid].min()), float(d[:mid].max())), (float(d[mid:].min()), float(d[mid:].max()))
        at = len(self.nodes)
        self.nodes.append(())
        a, b = self._build(lo, lo + mid), self._build(lo + mid, hi)
        self.nodes[at] = (vantage, inner, outer, a, b)
        return at

    def search(self, q: np.ndarray, k: int, factor: float) -> tuple[np.ndarray, np.ndarray]:
        """Row numbers and distances of the k nearest of each query; -1 and infinity where there are fewer."""
        n = len(q)
        self.best, self.found, self.q, self.k, self.factor = np.full((n, k), np.inf), np.full((n, k), -1, np.int64), q, k, factor
        self.visited = np.zeros(n, np.int64)
        self._home(self.root, np.arange(n))
        self._walk(self.root, np.arange(n))
        return self.found, self.best

    def within(self, q: np.ndarray, bound: np.ndarray, factor: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Query and row numbers of all pairs no farther than the query's bound, leaf by leaf."""
        stack = [(self.root, np.arange(len(q)))]
        while stack:
            at, who = stack.pop()
            if not len(who):
                continue
            node = self.nodes[at]
            if node[0] is None:
                rows = self.order[node[1]:node[2]]
                d = np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (q[who] @ self.x[rows].T)))
                a, b = np.nonzero(d <= bound[who][:, None])
                if len(a):
                    yield who[a], rows[b]
                continue
            d = _distance(q[who], self.x[node[0]])
            for side, (lo, hi) in zip(node[3:], node[1:3], strict=True):
                gap = np.maximum(0.0, np.maximum(lo - d, d - hi))
                stack.append((side, who[gap * factor <= bound[who] + SLACK]))

    def _home(self, at: int, who: np.ndarray) -> None:
        """Each query to the leaf that it would lie in."""
        self.home = np.full(len(self.q), -1)
        stack = [(at, who)]
        while stack:
            at, who = stack.pop()
            if not len(who):
                continue
            node = self.nodes[at]
            if node[0] is None:
                self._leaf(at, who)
                self.home[who] = at
                continue
            d = _distance(self.q[who], self.x[node[0]])
            near = d <= (node[1][1] + node[2][0]) / 2
            stack += [(node[3], who[near]), (node[4], who[~near])]

    def _walk(self, at: int, who: np.ndarray) -> None:
        if not len(who):
            return
        node = self.nodes[at]
        if node[0] is None:
            self._leaf(at, who[self.home[who] != at])
            return
        d = _distance(self.q[who], self.x[node[0]])
        gaps = [np.maximum(0.0, np.maximum(lo - d, d - hi)) for lo, hi in node[1:3]]
        # the side that more of the queries are nearer to goes first
        for side in sorted((0, 1), key=lambda s: float(gaps[s].mean())):
            left = gaps[side] * self.factor <= self.best[who, -1] + SLACK
            self._walk(node[3 + side], who[left])

    def _leaf(self, at: int, who: np.ndarray) -> None:
        _, lo, hi = self.nodes[at]
        if not len(who) or lo == hi:
            return
        rows = self.order[lo:hi]
        self.visited[who] += hi - lo
        d = np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (self.q[who] @ self.x[rows].T)))
        k = self.k
        every = np.concatenate([self.best[who], d], axis=1)
        ids = np.concatenate([self.found[who], np.broadcast_to(rows, (len(who), len(rows)))], axis=1)
        if every.shape[1] > k:
            pick = np.argpartition(every, k - 1, axis=1)[:, :k]
            every, ids = np.take_along_axis(every, pick, 1), np.take_along_axis(ids, pick, 1)
        order = np.argsort(every, axis=1, kind="stable")
        self.best[who], self.found[who] = np.take_along_axis(every, order, 1), np.take_along_axis(ids, order, 1)


def _distance(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (x @ y)))


def cosine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row, summed component by component in order, so that any engine can repeat it."""
    dot, na, nb = np.zeros(len(a)), np.zeros(len(a)), np.zeros(len(a))
    for i in range(a.shape[1]):
        dot += a[:, i] * b[:, i]
        na += a[:, i] * a[:, i]
        nb += b[:, i] * b[:, i]
    return dot / (np.sqrt(na) * np.sqrt(nb))


class Shard:
    """The vectors of one shard, their tree, and the rows that each distinct vector stands for."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, leaf: int = LEAF):
        order = np.argsort(ids, kind="stable")
        self.ids = ids[order]
        self.raw, group = np.unique(x[order], axis=0, return_inverse=True)
        group = group.ravel()
        self.members = np.argsort(group, kind="stable")  # rows of a group stand by id
        self.starts = np.concatenate([[0], np.cumsum(np.bincount(group, minlength=len(self.raw)))])
        self.tree = Tree(_unit(self.raw), leaf)

    def search(self, qid: np.ndarray, q: np.ndarray, k: int, factor: float) -> pd.DataFrame:
        """The k nearest rows for each query: query_id, vec_id, score."""
        asked = _unit(q)
        # a query's own row may take a place
        _, best = self.tree.search(asked, k + 1, factor)
        bound = np.where(np.isfinite(best[:, -1]), best[:, -1], 2.0) + SLACK
        out, held, rows = _nothing(), [], 0
        for out_q, groups in self.tree.within(asked, bound, factor):
            scores = cosine(q[out_q], self.raw[groups])
            for j in range(k + 1):  # the j-th smallest id of each group
                has = self.starts[groups] + j < self.starts[groups + 1]
                part = pd.DataFrame({"query_id": qid[out_q[has]], "vec_id": self.ids[self.members[self.starts[groups[has]] + j]], "score": scores[has]})
                held.append(part[part["query_id"] != part["vec_id"]])
                rows += len(held[-1])
            if rows > HELD_ROWS:
                out, held, rows = _best_of([out, *held], k), [], 0
        return _best_of([out, *held], k)


def _unit(m: np.ndarray) -> np.ndarray:
    # first by the largest component, so that no square is lost
    m = m / np.abs(m).max(axis=1)[:, None]
    return m / np.sqrt((m * m).sum(axis=1))[:, None]


def _nothing() -> pd.DataFrame:
    return pd.DataFrame({"query_id": np.empty(0, np.int64), "vec_id": np.empty(0, np.int64), "score": np.empty(0)})


def _best_of(parts: list[pd.DataFrame], k: int) -> pd.DataFrame:
    return pd.concat(parts).sort_values(["query_id", "score", "vec_id"], ascending=[True, False, True]).groupby("query_id", sort=False).head(k)


def search_shard(index: pd.DataFrame, queries: pd.DataFrame, k: int, factor: float, leaf: int = LEAF) -> pd.DataFrame:
    """One shard and one block of queries, both id and v: query_id, vec_id, score."""
    if not len(index) or not len(queries):
        return _nothing()
    matrix = lambda v: np.array(v.tolist(), np.float64)
    return Shard(index["id"].to_numpy(), matrix(index["v"]), leaf).search(queries["id"].to_numpy(), matrix(queries["v"]), k, factor)


def usable(vectors: DataFrame, vec_id: str, embedding: str, length: int | None = None) -> DataFrame:
    """id, v (doubles) of the vectors that can take part. Without ``length``, that of most vectors is that of all."""
    v = vectors.select(F.col(vec_id).cast("long").alias("id"), F.col(embedding).cast("array<double>").alias("v")).where(F.col("id").isNotNull() & F.col("v").isNotNull())
    v = v.where(F.forall("v", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists("v", lambda c: c != 0))
    if length is None:
        most = v.groupBy(F.size("v").alias("n")).count().orderBy(F.col("count").desc(), "n").limit(1).collect()
        length = most[0]["n"] if most else None
    return v if length is None else v.where(F.size("v") == length)


def nearest(vectors: DataFrame, queries: DataFrame | None = None, vec_id: str = "vec_id", embedding: str = "embedding", k: int = K, factor: float = FACTOR, every: int = EVERY, shard_rows: int = SHARD_ROWS, block_rows: int = BLOCK_ROWS, length: int | None = None) -> DataFrame:
    """query_id, rank, vec_id, score. Without ``queries``, rows whose id is divisible by ``every`` are the queries."""
    spark = vectors.sparkSession
    ship(spark)
    index = usable(vectors, vec_id, embedding, length)
    asked = index.where(F.col("id") % every == 0) if queries is None else usable(queries, vec_id, embedding, length)
    asked = materialize(asked)
    n = vectors.count()
    shards = max(1, -(-n // shard_rows), min(spark.sparkContext.defaultParallelism, n // 2000))
    left = index.select(F.pmod(F.xxhash64(F.col("id")), F.lit(shards)).cast("int").alias("shard"), F.lit(0).alias("kind"), "id", "v")
    right = asked.select(F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.lit(1).alias("kind"), "id", "v")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {0: [], 1: []}  # ids and vectors of the shard, then of a block of its queries
        now = shard = None

        def block() -> pa.RecordBatch:
            ids, x = (np.concatenate([p[i] for p in held[1]]) for i in (0, 1))
            held[1] = []
            return pa.RecordBatch.from_pandas(shard.search(ids, x, k, factor), preserve_index=False)

        for batch in batches:
            parts, kinds, ids = (batch[c].to_numpy() for c in ("shard", "kind", "id"))
            x = batch["v"].flatten().to_numpy().reshape(len(ids), -1)
            cuts = np.flatnonzero(np.diff(parts.astype(np.int64) * 2 + kinds)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, len(ids)], strict=True):
                if lo == hi:
                    continue
                if parts[lo] != now:
                    if held[1] and shard is not None:
                        yield block()
                    now, shard, held = parts[lo], None, {0: [], 1: []}
                kind = int(kinds[lo])
                if kind == 1 and shard is None:
                    if not held[0]:
                        continue  # a shard without vectors
                    shard = Shard(*(np.concatenate([p[i] for p in held[0]]) for i in (0, 1)))
                    held[0] = []
                held[kind].append((ids[lo:hi], x[lo:hi]))
                if kind == 1 and sum(len(p[0]) for p in held[1]) >= block_rows:
                    yield block()
        if held[1] and shard is not None:
            yield block()

    rows = left.unionByName(right).repartition(shards, "shard").sortWithinPartitions("shard", "kind", "id")
    part = rows.mapInArrow(run, "query_id long, vec_id long, score double")
    by_score = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return part.withColumn("rank", F.row_number().over(by_score)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"))


def _sum(a: str, b: str) -> str:
    return f"list_reduce(list_prepend(0.0::DOUBLE, list_transform(list_zip({a}, {b}), lambda z: z[1] * z[2])), lambda s, x: s + x)"


ORACLE = f"""
WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
u AS (SELECT vec_id, e, sqrt({_sum('e', 'e')}) AS n FROM v WHERE e IS NOT NULL),
g AS (SELECT * FROM u WHERE n > 0 AND isfinite(n)),
s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, {_sum('q.e', 'c.e')} / (q.n * c.n) AS score
      FROM g q JOIN g c ON q.vec_id % {EVERY} = 0 AND q.vec_id <> c.vec_id)
SELECT query_id, CAST(r AS INT) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM s) WHERE r <= {K}"""
