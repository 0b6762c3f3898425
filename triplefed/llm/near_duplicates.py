"""Near duplicates by a chosen-path set similarity join.

A document's set holds the hashes of its word shingles. Documents with equal sets are one class, whose first document
speaks for it; classes are what is joined. Independent trees branch the classes: at each level one, at some nodes two, of
the tree's own minwise tokens are taken, and a class goes to the branch of its value of the token. Nodes of at most
``node_rows`` are compared exhaustively on sketches of minwise bytes; larger ones branch again, down to ``depth``. There
are so many trees that a link at the very threshold stays together, down to the last level, in one of them with
probability ``recall`` or more.

A node that is still larger at ``depth`` is settled without loss. Links of its classes to the two most similar of a few
pivots come first, and only tell what is joined already. Then all its classes outside the largest of these groups meet
each other and that group, block against block, so work grows with the square of what is left apart, not of alike copies.

A pair is looked at in its first common node only. Classes without a candidate stop there; the full sets of the others
are brought to their nodes, where candidates are confirmed exactly and only links that join something come out, so that
no group is ever expanded into all its pairs. Links are joined into components in rounds of star contractions. Nothing
but counts goes to the driver.

Defined cases: A-Z are lower-cased; with fewer words than a shingle has, the whole sequence is one; a null, empty or blank
text has an empty set, is linked with nothing and is kept; rows of one id are one document, of whose texts the one with the
smallest fingerprint counts, and give one row; rows without an id have no component and are kept each; an empty table gives
no rows; only named columns are read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.llm.common import materialize, ship, table

#: Bytes of minwise tokens to compare.
SKETCH = 128
#: Tokens of a tree at a level.
TOKENS = 2
#: Least share of links at the very threshold that the trees bring together.
RECALL = 0.9999
NODE_ROWS, DEPTH = 4096, 2
#: How many standard deviations of the sketch a candidate may fall short of the threshold.
SLACK = 3.7
#: Word hashes that a task keeps.
CACHE = 200_000
PIVOTS = 64


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= CACHE:
            self.clear()
        self[word] = h = xxhash.xxh64_intdigest(word)
        return h


def shingles(text: str | None, words: int, hashes: WordHashes) -> np.ndarray:
    """The sorted distinct 64-bit hashes of the shingles."""
    w = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not w:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(hashes.__getitem__, w), np.uint64, len(w))
    k = min(words, len(h))
    out = np.zeros(len(h) - k + 1, np.uint64)
    for i in range(k):
        out = (out ^ h[i:len(h) - k + 1 + i]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    out = (out + np.uint64(k)) * np.uint64(0xBF58476D1CE4E5B9)
    return np.unique(out ^ (out >> np.uint64(32)))


def _coefficients(n: int) -> tuple[np.ndarray, np.ndarray]:
    r = np.random.RandomState(20_240_131)
    return r.randint(0, 2**32, n, np.uint32) | np.uint32(1), r.randint(0, 2**32, n, np.uint32)


def minwise(s: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    x = (s ^ (s >> np.uint64(32))).astype(np.uint32)
    out = np.full(len(a), 0xFFFFFFFF, np.uint32)
    for lo in range(0, len(x), 1024):
        np.minimum(out, (x[lo:lo + 1024, None] * a + b).min(axis=0), out=out)
    return out


def trees_for(similarity: float, depth: int, recall: float) -> int:
    """How many trees bring a pair of this similarity together, all levels down, with probability ``recall``. Only the
    first token of each node counts; where a node takes two, recall is better."""
    missed = 1 - similarity**depth
    return 1 if missed <= 0 else max(1, math.ceil(math.log(1 - recall) / math.log(missed)))


def fingerprint(s: np.ndarray) -> tuple[int, int]:
    """What equal sets share, and different ones don't."""
    if not len(s):
        return 0, 0
    f1 = np.bitwise_xor.reduce(s * np.uint64(0xD6E8FEB86659FD93) ^ (s >> np.uint64(17)))
    return int(f1.view(np.int64)), int((s * (s >> np.uint64(7) | np.uint64(1))).sum(dtype=np.uint64).view(np.int64))


def sketches(docs: DataFrame, words: int, tokens: int) -> DataFrame:
    """doc_id, n_shingles, f1, f2 (what equal sets share), paths, sketch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        a, b = _coefficients(tokens + SKETCH)
        for batch in batches:
            n, f1, f2, paths, sketch = [], [], [], [], []
            for text in batch["text"]:
                s = shingles(text.as_py(), words, hashes)
                m = minwise(s, a, b)
                n.append(len(s))
                both = fingerprint(s)
                f1.append(both[0])
                f2.append(both[1])
                paths.append(m[:tokens].view(np.int32))
                sketch.append((m[tokens:] >> np.uint32(11)).astype(np.uint8).tobytes())
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(n, pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), pa.array(paths, pa.list_(pa.int32())), pa.array(sketch, pa.binary())], names=["doc_id", "n_shingles", "f1", "f2", "paths", "sketch"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_shingles long, f1 long, f2 long, paths array<int>, sketch binary")


def full_sets(docs: DataFrame, words: int) -> DataFrame:
    """rep, f1, f2, set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            sets = [shingles(t.as_py(), words, hashes) for t in batch["text"]]
            both = [fingerprint(s) for s in sets]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array([f for f, _ in both], pa.int64()), pa.array([f for _, f in both], pa.int64()), pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], names=["rep", "f1", "f2", "set"])

    return docs.select("doc_id", "text").mapInArrow(run, "rep long, f1 long, f2 long, set array<long>")


def _branch(node, tree, level: int, depth: int, chance: float):
    """The values of a node's tokens, as the nodes below it: one, and another with this chance. No two trees or levels
    share a token."""
    at = (tree * depth + (level - 1)) * TOKENS
    below = lambda k: F.xxhash64(node, F.lit(k), F.get("paths", at + k))
    more = F.pmod(F.xxhash64(node, F.lit(3)), F.lit(1000)) < int(1000 * chance)
    return F.array_distinct(F.when(more, F.array(below(0), below(1))).otherwise(F.array(below(0))))


def nodes_of(classes: DataFrame, similarity: float, trees: int, node_rows: int, depth: int) -> tuple[DataFrame, DataFrame | None]:
    """(node, rep) of all nodes to compare as they are, and (node, rep, size) of the larger ones that are left."""
    chance = 1 / similarity - 1
    paths = classes.select("rep", "paths")
    rows = paths.select("rep", F.explode(F.sequence(F.lit(0), F.lit(trees - 1))).alias("tree"), "paths")
    rows = rows.select("rep", "tree", F.explode(_branch(F.xxhash64("tree"), F.col("tree"), 1, depth, chance)).alias("node"))
    done: list[DataFrame] = []
    left = None
    for level in range(1, depth + 1):
        rows = materialize(rows)
        sizes = materialize(rows.groupBy("node").agg(F.count(F.lit(1)).alias("size")).where("size > 1"))
        done.append(rows.join(sizes.where(F.col("size") <= node_rows).select("node"), "node").select("node", "rep"))
        large = sizes.where(F.col("size") > node_rows)
        if large.isEmpty():
            break
        wide = rows.join(large, "node")
        if level == depth:
            left = materialize(wide.select("node", "rep", "size"))
        else:
            rows = wide.join(paths, "rep").select("rep", "tree", F.explode(_branch(F.col("node"), F.col("tree"), level + 1, depth, chance)).alias("node"))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return materialize(out.distinct()), left


def with_pivots(wide: DataFrame, pivots: int) -> DataFrame:
    """a, b: each class with the two most similar (one, of fewer than 16) of about so many classes of its node drawn by
    hash. Chance settles ties, so alike classes spread. ``wide``: node, rep, size, sketch."""
    draw = F.pmod(F.xxhash64("rep", "node"), F.lit(1 << 40)) < (F.lit(pivots) / F.col("size") * (1 << 40)).cast("long")
    drawn = materialize(wide.where(draw).groupBy("node").agg(F.collect_list(F.struct("rep", "sketch")).alias("pivots")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple[int, int]] = []
            for rep, sketch, some in zip(batch["rep"].to_pylist(), batch["sketch"].to_pylist(), batch["pivots"].to_pylist(), strict=True):
                ids = np.array([p["rep"] for p in some], np.int64)
                m = np.frombuffer(b"".join(p["sketch"] for p in some), np.uint8).reshape(-1, SKETCH)
                alike = (m == np.frombuffer(sketch, np.uint8)).sum(axis=1).astype(float)
                alike += ((ids ^ np.int64(rep)).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(44)) / float(1 << 21)
                out += [(min(rep, int(ids[k])), max(rep, int(ids[k]))) for k in np.argsort(-alike)[:2 if len(ids) >= 16 else 1] if ids[k] != rep]
            a, b = zip(*out) if out else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return wide.join(drawn, "node").select("rep", "sketch", "pivots").mapInArrow(run, "a long, b long")


def blocks(large: DataFrame, joined: DataFrame, node_rows: int) -> DataFrame:
    """node, rep, known, part: large nodes cut into pairs of blocks, so that any two classes that are not ``joined`` (rep,
    component) yet meet in one. ``known`` is what a class is joined to; classes of one ``part`` meet in another pair."""
    half = max(1, node_rows // 2)
    rows = materialize(large.join(joined, "rep", "left").select("node", "rep", "size", F.coalesce("component", "rep").alias("known")))
    most = rows.groupBy("node", "known").agg(F.count(F.lit(1)).alias("n")).groupBy("node").agg(F.max(F.struct("n", "known")).alias("most"))
    cut = lambda n: F.ceil(n / F.lit(half)).cast("int")
    rows = rows.join(materialize(most), "node").where("size > most.n").withColumn("apart", cut(F.col("size") - F.col("most.n"))).withColumn("alike", cut(F.col("most.n")))
    inside = F.col("known") == F.col("most.known")
    spread = F.xxhash64("rep", "node")
    rows = rows.withColumn("block", F.when(inside, F.col("apart") + F.pmod(spread, "alike")).otherwise(F.pmod(spread, "apart")).cast("int"))
    others = F.when(inside, F.sequence(F.lit(0), F.col("apart") - 1)).otherwise(F.sequence(F.lit(0), F.col("apart") + F.col("alike") - 1))
    rows = rows.select("node", "rep", "known", "block", F.explode(others).alias("other"))
    cell = F.xxhash64("node", F.least("block", "other"), F.greatest("block", "other"))
    return rows.select(cell.alias("node"), "rep", "known", F.when(F.col("block") == F.col("other"), F.col("rep")).otherwise(F.col("block").cast("long")).alias("part"))


def _by_node(batches: Iterator[pa.RecordBatch]) -> Iterator[list[pa.RecordBatch]]:
    """The rows of one node after another, from batches sorted by node; a node is bounded, so is what is held."""
    held: list[pa.RecordBatch] = []
    current = None
    for batch in batches:
        nodes = batch["node"].to_numpy()
        lo = 0
        for hi in [*(np.flatnonzero(np.diff(nodes)) + 1).tolist(), len(nodes)]:
            if hi == lo:
                continue
            if held and nodes[lo] != current:
                yield held
                held = []
            held.append(batch.slice(lo, hi - lo))
            current = nodes[lo]
            lo = hi
    if held:
        yield held


class Node:
    """The classes of one node: their sketches, sizes, and all the nodes that each is in, or what they are known to be
    joined to and their parts."""

    def __init__(self, held: list[pa.RecordBatch], least: int, ratio: float):
        column = lambda name: np.concatenate([h[name].to_numpy(zero_copy_only=False) for h in held])
        self.id = held[0]["node"][0].as_py()
        self.rep, self.n = column("rep"), column("n")
        self.sketch = np.frombuffer(b"".join(x for h in held for x in h["sketch"].to_pylist()), np.uint8).reshape(-1, SKETCH)
        self.blocked = "part" in held[0].schema.names
        if self.blocked:
            self.known, self.part = column("known"), column("part")
        else:
            lists = [x for h in held for x in h["nodes"].to_pylist()]
            self.nodes = np.empty((len(lists), max(map(len, lists))), np.int64)
            for i, x in enumerate(lists):
                self.nodes[i] = x + [x[0]] * (self.nodes.shape[1] - len(x))
        self.least, self.ratio = least, ratio

    def __len__(self) -> int:
        return len(self.rep)

    def candidates(self, i: int) -> np.ndarray:
        """Later classes whose sketches are alike enough and whose first common node is this one."""
        rest = slice(i + 1, len(self))
        may = np.minimum(self.n[i], self.n[rest]) >= self.ratio * np.maximum(self.n[i], self.n[rest])
        if self.blocked:
            may &= (self.known[rest] != self.known[i]) & (self.part[rest] != self.part[i])
        fits = may.nonzero()[0] + i + 1
        if len(fits):
            fits = fits[(self.sketch[fits] == self.sketch[i]).sum(axis=1) >= self.least]
        if len(fits) and not self.blocked:
            common = (self.nodes[fits][:, :, None] == self.nodes[i][None, None, :]).any(axis=2)
            fits = fits[np.where(common, self.nodes[fits], np.iinfo(np.int64).max).min(axis=1) == self.id]
        return fits


def worth_confirming(rows: DataFrame, least: int, ratio: float) -> DataFrame:
    """node, rep of the classes that have a candidate in the node. ``rows``: node, rep, n, sketch, and nodes or known, part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nodes: list[int] = []
        reps: list[np.ndarray] = []
        for held in _by_node(batches):
            node = Node(held, least, ratio)
            has = np.zeros(len(node), bool)
            for i in range(len(node) - 1):
                found = node.candidates(i)
                if len(found):
                    has[i] = has[found] = True
            if has.any():
                reps.append(node.rep[has])
                nodes += [node.id] * len(reps[-1])
            if len(nodes) > 50_000:
                yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(np.concatenate(reps), pa.int64())], names=["node", "rep"])
                nodes, reps = [], []
        if nodes:
            yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(np.concatenate(reps), pa.int64())], names=["node", "rep"])

    return rows.repartition("node").sortWithinPartitions("node", "rep").mapInArrow(run, "node long, rep long")


def confirmed(rows: DataFrame, least: int, ratio: float, percent: int) -> DataFrame:
    """a, b: links that join what a node knows as apart, confirmed on full sets. ``rows``: also set.

    A class is compared with all its candidates at once: its set is marked among the node's shingles, and the marks
    under each candidate's set are summed. Candidates that are joined already are passed over, so a node gives fewer
    links than it has classes.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a: list[int] = []
        b: list[int] = []
        for held in _by_node(batches):
            node = Node(held, least, ratio)
            _, ids = np.unique(np.concatenate([h["set"].flatten().to_numpy() for h in held]), return_inverse=True)
            starts = np.concatenate([[0], np.cumsum(node.n)])
            label = np.unique(node.known, return_inverse=True)[1] if node.blocked else np.arange(len(node))
            marks = np.zeros(int(ids.max()) + 1, np.int32)
            for i in range(len(node) - 1):
                found = node.candidates(i)
                found = found[label[found] != label[i]]
                if not len(found):
                    continue
                own = ids[starts[i]:starts[i + 1]]
                marks[own] = 1
                for lo in range(0, len(found), 256):
                    some = found[lo:lo + 256]
                    of = np.concatenate([ids[starts[j]:starts[j + 1]] for j in some])
                    both = np.add.reduceat(marks[of], np.concatenate([[0], np.cumsum(node.n[some])[:-1]])).astype(np.int64)
                    for j in some[100 * both >= percent * (node.n[i] + node.n[some] - both)]:
                        if label[j] != label[i]:
                            a.append(int(node.rep[i]))
                            b.append(int(node.rep[j]))
                            label[label == label[j]] = label[i]
                marks[own] = 0
            if len(a) > 50_000:
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])
                a, b = [], []
        if a:
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return rows.repartition("node").sortWithinPartitions("node", "rep").mapInArrow(run, "a long, b long")


def components(links: DataFrame) -> DataFrame:
    """rep, component (its smallest member) of all ends of the links, by star contractions until nothing changes."""
    edges = materialize(links.select("a", "b").where("a <> b").distinct())
    if edges.isEmpty():
        return edges.select(F.col("a").alias("rep"), F.col("b").alias("component"))
    before = None
    while True:
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
        low = materialize(both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m")))
        # larger neighbours go to the smallest
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        edges = materialize(large)
        # and every node's smaller neighbours go to the smallest of them
        down = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        low = materialize(down.groupBy("u").agg(F.min("v").alias("m")))
        small = down.join(low, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").unionByName(low.select(F.col("u").alias("a"), F.col("m").alias("b"))).distinct()
        edges = materialize(small)
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.countDistinct("b"), F.max("a")).collect()[0]
        if now == before:
            return edges.groupBy(F.col("a").alias("rep")).agg(F.min("b").alias("component"))
        before = now


def duplicate_groups(docs: DataFrame, words: int = 5, percent: int = 80, trees: int | None = None, node_rows: int = NODE_ROWS, depth: int = DEPTH, recall: float = RECALL) -> DataFrame:
    """Per document: doc_id, n_shingles, component_id, kept. Links: 100 * intersection >= ``percent`` * union. Without
    ``trees``, there are as many as ``recall`` needs."""
    spark = docs.sparkSession
    ship(spark)
    similarity = percent / 100
    known = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    trees = trees or trees_for(similarity, depth, recall)
    marked = materialize(sketches(known, words, trees * depth * TOKENS))
    # ids that come again: one of their texts is chosen, here and wherever sets are made
    same_id = marked.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count(F.lit(1)).alias("times"), F.min(F.struct("f1", "f2")).alias("own"))
    again = materialize(same_id.where("times > 1").select("doc_id", F.col("own.f1").alias("own1"), F.col("own.f2").alias("own2")))
    if again.isEmpty():
        again = None
    else:
        marked = marked.join(again, "doc_id", "left").where("own1 IS NULL OR (f1 = own1 AND f2 = own2)")
        chosen = marked.where("own1 IS NOT NULL").dropDuplicates(["doc_id"])
        marked = materialize(marked.where("own1 IS NULL").unionByName(chosen).drop("own1", "own2"))
    filled = marked.where("n_shingles > 0 AND doc_id IS NOT NULL")
    same = ["f1", "f2", "n_shingles"]
    classes = materialize(filled.groupBy(*same).agg(F.min("doc_id").alias("rep")))
    member = materialize(filled.select("doc_id", *same).join(classes, same).select("doc_id", "rep"))
    reps = filled.join(classes.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi")
    reps = materialize(reps.select(F.col("doc_id").alias("rep"), F.col("n_shingles").alias("n"), "paths", "sketch"))
    nodes, large = nodes_of(reps, similarity, trees, node_rows, depth)
    least = int(SKETCH * (similarity - SLACK * (similarity * (1 - similarity) / SKETCH) ** 0.5))
    places = nodes.groupBy("rep").agg(F.sort_array(F.collect_list("node")).alias("nodes"))  # a few for each tree
    wide = materialize(reps.drop("paths").join(places, "rep"))
    links = within(nodes.join(wide, "rep").select("node", "rep", "n", "sketch", "nodes"), known, words, least, similarity, percent, again)
    if large is not None:
        flat = reps.select("rep", "n", "sketch")
        pairs = materialize(with_pivots(large.join(flat, "rep"), max(2, min(PIVOTS, node_rows // 4))).distinct())
        ends = pairs.select(F.col("a").alias("rep")).unionByName(pairs.select(F.col("b").alias("rep"))).distinct()
        found = materialize(confirm(pairs, sets_of(known, ends, words, again), percent).where("linked").select("a", "b"))
        links = materialize(links.unionByName(found))
        cells = materialize(blocks(large, components(links), node_rows).join(flat, "rep").select("node", "rep", "n", "sketch", "known", "part"))
        links = links.unionByName(within(cells, known, words, least, similarity, percent, again))
    label = materialize(components(links))
    out = marked.select("doc_id", "n_shingles").join(member, "doc_id", "left").join(label, "rep", "left")
    # a component's smallest class representative is its smallest document: representatives are the smallest of theirs
    out = out.withColumn("component_id", F.coalesce("component", "rep", "doc_id"))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def sets_of(docs: DataFrame, reps: DataFrame, words: int, again: DataFrame | None) -> DataFrame:
    """rep, set of the classes in ``reps``. ``again``: ids with several texts, and the fingerprints of those that count."""
    sets = full_sets(docs.join(reps.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi"), words)
    if again is not None:
        sets = sets.join(again.withColumnRenamed("doc_id", "rep"), "rep", "left").where("own1 IS NULL OR (f1 = own1 AND f2 = own2)").dropDuplicates(["rep"])
    return materialize(sets.select("rep", "set"))


def within(rows: DataFrame, docs: DataFrame, words: int, least: int, ratio: float, percent: int, again: DataFrame | None) -> DataFrame:
    """a, b: links inside the nodes of ``rows``, confirmed on the full sets of classes that have a candidate."""
    near = materialize(worth_confirming(rows, least, ratio))
    sets = sets_of(docs, near.select("rep").distinct(), words, again)
    return materialize(confirmed(near.join(rows, ["node", "rep"]).join(sets, "rep").select(*rows.columns, "set"), least, ratio, percent))


def confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    a = sets.select(F.col("rep").alias("a"), F.col("set").alias("sa"))
    b = sets.select(F.col("rep").alias("b"), F.col("set").alias("sb"))
    both = F.size(F.array_intersect("sa", "sb")).cast("long")
    return pairs.join(a, "a").join(b, "b").select("a", "b", (100 * both >= percent * (F.size("sa") + F.size("sb") - both)).alias("linked"))


def first_of_groups(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """The documents without all but one of each group: a stage of a pipeline."""
    # the ids that go are fewer than those that stay, and few enough, mostly, that no text has to move
    gone = materialize(duplicate_groups(docs, words, percent).where("NOT kept").select(F.col("doc_id").alias("__id")).distinct())
    first = docs.join(gone, docs["doc_id"] == gone["__id"], "left_anti")
    return first.select(*(docs[c] for c in docs.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return duplicate_groups(table(spark, sf_dir, "documents"), words=3, percent=85)
