"""Scans of one pattern, the central answer, and the main index's access paths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from triplefed.plans.order import order_patterns
from triplefed.query import Pattern, QueryGraph, is_var
from triplefed.stats import Stats


def scan_pattern(t: DataFrame, pattern: Pattern, keep_home: bool = False) -> DataFrame:
    """Bindings of the pattern's variables: selections on constants (pushed to the scan), equal columns for a variable
    that comes twice, and a projection. A pattern without variables gives at most one row, with the column ``found``."""
    for column, term in zip("spo", pattern, strict=True):
        if not is_var(term):
            t = t.where(F.col(column) == term)
    first: dict[str, str] = {}
    for column, term in zip("spo", pattern, strict=True):
        if is_var(term):
            if term in first:
                t = t.where(F.col(column) == F.col(first[term]))
            else:
                first[term] = column
    home = ["home"] if keep_home else []
    if not first:
        return t.select(F.lit(True).alias("found"), *home).limit(1)
    return t.select(*(F.col(c).alias(v[1:]) for v, c in first.items()), *home)


def natural_join(a: DataFrame, b: DataFrame, how: str = "inner") -> DataFrame:
    shared = [c for c in b.columns if c in a.columns]
    if shared:
        return a.join(b, shared, how)
    return a.crossJoin(b)  # parts of a query that share no variable: their product is the answer


def run_centralised(t: DataFrame, q: QueryGraph, stats: Stats | None = None, semantics: str = "homomorphism") -> DataFrame:
    """The reference answer: ordinary joins over all triples in one place."""
    out = None
    for i in order_patterns(q, stats):
        part = scan_pattern(t, q.patterns[i])
        out = part if out is None else natural_join(out, part)
    return project(out, q, semantics)


def project(rows: DataFrame, q: QueryGraph, semantics: str = "homomorphism") -> DataFrame:
    names = [v[1:] for v in q.variables]
    if semantics == "injective":
        ends = [v[1:] for v in q.vertices if is_var(v)]
        for i, a in enumerate(ends):
            for b in ends[i + 1:]:
                rows = rows.where(F.col(a) != F.col(b))
    return rows.select(*names) if names else rows


class MainIndex:
    """All triples of the federation: a folder for each predicate, one copy sorted by subject and one by object.

    The three access paths are selections: the predicate prunes folders, the bound end prunes row groups by their minima
    and maxima in the copy that is sorted by it. A predicate's rows are dealt into ``files`` by hash of the subject in both
    copies, so neither a predicate nor an object that a third of all triples has comes to one task.

    Batches are appended as they come. Rows carry the number of the batch that they were ``born`` in; deleted ones are
    listed in a table of their own with the batch that they ``died`` in, and are left out when read, until ``compact``.
    """

    def __init__(self, triples: DataFrame, both: bool = True, files: int = 8):
        self.columns = [c for c in ("s", "p", "o", "home") if c in triples.columns]
        self.files = files
        self.spark = triples.sparkSession
        self.ends = ("s", "o") if both else ("s",)
        self._lay(triples)

    def _lay(self, triples: DataFrame) -> None:
        from triplefed.storage import new_folder

        self.at = {end: new_folder(self.spark) for end in self.ends}
        self.dead: DataFrame | None = None
        self.born = self.died = 0
        for end in self.ends:
            self._write(triples, end, 0)

    def _write(self, triples: DataFrame, end: str, number: int) -> None:
        dealt = triples.select(*self.columns).repartition("p", F.pmod(F.xxhash64("s"), F.lit(self.files))).sortWithinPartitions("p", end)
        dealt.withColumn("born", F.lit(number)).write.mode("append").option("maxRecordsPerFile", 5_000_000).partitionBy("p").parquet(self.at[end])

    def _copy(self, end: str) -> DataFrame:
        kinds = {"home": "int"}
        rows = self.spark.read.schema(", ".join(f"{c} {kinds.get(c, 'string')}" for c in self.columns if c != "p") + ", born int, p string").parquet(self.at[end if end in self.at else "s"])
        if self.dead is not None:
            gone = self.dead.select("s", "p", "o", "died")
            rows = rows.join(gone, [*(rows[c] == gone[c] for c in "spo"), gone["died"] > rows["born"]], "left_anti")
        return rows.select(*self.columns)

    @property
    def by_s(self) -> DataFrame:
        return self._copy("s")

    @property
    def by_o(self) -> DataFrame:
        return self._copy("o")

    def by_predicate(self, p: str) -> DataFrame:
        return self.by_s.where(F.col("p") == p).select("s", "o")

    def by_ps(self, p: str, s: str) -> DataFrame:
        return self.by_s.where((F.col("p") == p) & (F.col("s") == s)).select("s", "o")

    def by_po(self, p: str, o: str) -> DataFrame:
        return self.by_o.where((F.col("p") == p) & (F.col("o") == o)).select("s", "o")

    def exists(self, s: str, p: str, o: str) -> bool:
        return not self.by_s.where((F.col("p") == p) & (F.col("s") == s) & (F.col("o") == o)).isEmpty()

    def triples(self) -> DataFrame:
        return self.by_s

    def insert(self, batch: DataFrame, number: int) -> int:
        """Appends what isn't there yet; writes as much as the batch has."""
        from triplefed.storage import save

        new = save(batch.select(*self.columns).dropDuplicates(["s", "p", "o"]).join(self.triples().select("s", "p", "o"), ["s", "p", "o"], "left_anti"))
        n = new.count()
        if n:
            for end in self.ends:
                self._write(new, end, number)
            self.born += n
        return n

    def delete(self, batch: DataFrame, number: int) -> int:
        """Lists what is there and goes; writes as much as the batch has."""
        from triplefed.storage import save

        gone = save(batch.select("s", "p", "o").distinct().join(self.triples().select("s", "p", "o"), ["s", "p", "o"], "left_semi").withColumn("died", F.lit(number)))
        n = gone.count()
        if n:
            self.dead = gone if self.dead is None else self.dead.unionByName(gone)
            self.died += n
        return n

    def compact(self) -> None:
        """Writes what is live anew."""
        self._lay(self.triples())
