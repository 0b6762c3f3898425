"""Line-based triples as a data source of the session: ``spark.read.format("triple_lines")``, in batches or as a stream.

A partition for each file. Where the session pushes filters to Python sources, equality of the predicate is taken over from the query, so
lines of other predicates are never turned into rows. Sessions by themselves push none, and refuse a reader that takes any.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def source(pushdown: bool = False):
    """The class, made here so that it travels to workers by value and they need nothing of this package."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, EqualTo, InputPartition

    line = r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)")\s*\.\s*$'

    def files(path: str) -> list[str]:
        from pyarrow import fs

        system, at = fs.FileSystem.from_uri(path if "://" in path else f"file://{path}")
        found = system.get_file_info(fs.FileSelector(at, recursive=True))
        return sorted(f.path for f in found if f.is_file and not f.base_name.startswith(("_", ".")))

    def rows(path: str, name: str, predicate: str | None):
        import re

        from pyarrow import fs

        system, _ = fs.FileSystem.from_uri(path if "://" in path else f"file://{path}")
        fits = re.compile(line).match
        plain = {"n": "\n", "t": "\t", "r": "\r"}
        with system.open_input_stream(name) as f:
            rest = b""
            while chunk := f.read(1 << 20):
                *full, rest = (rest + chunk).split(b"\n")
                yield from parsed(full, fits, plain, predicate)
            yield from parsed([rest], fits, plain, predicate)

    def parsed(lines, fits, plain, predicate):
        import re

        for raw in lines:
            m = fits(raw.decode("utf-8", "replace"))
            if m and (predicate is None or m[2] == predicate):
                o = m[3] if m[3] is not None else re.sub(r"\\(.)", lambda x: plain.get(x[1], x[1]), m[4])
                yield (m[1], m[2], o)

    class Reader(DataSourceReader):
        def __init__(self, path: str):
            self.path, self.predicate = path, None

        def partitions(self):
            return [InputPartition(name) for name in files(self.path)]

        def read(self, partition):
            if partition.value is not None:
                yield from rows(self.path, partition.value, self.predicate)

    class PushedReader(Reader):
        def pushFilters(self, filters):
            for f in filters:
                if self.predicate is None and isinstance(f, EqualTo) and f.attribute == ("p",):
                    self.predicate = f.value
                else:
                    yield f

    class StreamReader(DataSourceStreamReader):
        def __init__(self, path: str):
            self.path = path

        def initialOffset(self):
            return {"files": 0}

        def latestOffset(self):
            return {"files": len(files(self.path))}

        def partitions(self, start, end):
            return [InputPartition(name) for name in files(self.path)[start["files"]:end["files"]]]

        def read(self, partition):
            yield from rows(self.path, partition.value, None)

    class TripleLines(DataSource):
        @classmethod
        def name(cls):
            return "triple_lines"

        def schema(self):
            return "s string, p string, o string"

        def reader(self, schema):
            return PushedReader(self.options["path"]) if pushdown else Reader(self.options["path"])

        def streamReader(self, schema):
            return StreamReader(self.options["path"])

    return TripleLines


def register(spark: SparkSession, pushdown: bool | None = None) -> None:
    """``pushdown``: whether the session pushes filters to Python sources; by default what it says itself."""
    if pushdown is None:
        pushdown = spark.conf.get("spark.sql.python.filterPushdown.enabled", "false") == "true"
    spark.dataSource.register(source(pushdown))


def round_trip(spark: SparkSession, t: DataFrame) -> DataFrame:
    """Written as lines and read again by the source."""
    from triplefed.sources.formats import write_ntriples
    from triplefed.storage import root

    register(spark)
    path = f"{root(spark)}/formats/{uuid.uuid4().hex}"
    write_ntriples(t, path)
    return spark.read.format("triple_lines").load(path)
