"""Python functions for what the JVM has no expression for, each in Arrow batches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def canonical_text():
    """The canonical form of a query's text."""

    def convert(texts: pd.Series) -> pd.Series:
        from triplefed.query import bgp, canonical

        return texts.map(lambda t: canonical(bgp(t))[0])

    return F.pandas_udf(convert, "string")


def gini_udaf():
    """The Gini coefficient of a group's loads."""

    def gini(loads: pd.Series) -> float:
        x = np.sort(loads.to_numpy(np.float64))
        n, total = len(x), x.sum()
        return float(((2 * np.arange(1, n + 1) - n - 1) * x).sum() / (n * total)) if total else 0.0

    return F.pandas_udf(gini, "double")


def parse_lines(spark, lines: list[str]) -> DataFrame:
    """line, s, p, o of those of the texts that are triples, by a table function over each."""
    from pyspark.sql.functions import udtf

    class ParseLine:
        def eval(self, text: str):
            import re

            m = re.match(r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)")\s*\.\s*$', text or "")
            if m:
                yield m[1], m[2], m[3] if m[3] is not None else m[4]

    parse = udtf(ParseLine, returnType="s: string, p: string, o: string")
    given = spark.createDataFrame(list(enumerate(lines)), "line int, text string")
    return given.lateralJoin(parse(F.col("text").outer())).select("line", "s", "p", "o")


def expand_table(spark, queries: DataFrame) -> DataFrame:
    """qid, place, s, p, o: a row for each pattern of a query's text (column ``text``), by a table function."""
    from pyspark.sql.functions import udtf

    class Expand:
        def eval(self, text: str):
            for i, part in enumerate(text.split(" . ")):
                yield (i, *part.split())

    expand = udtf(Expand, returnType="place: int, s: string, p: string, o: string")
    return queries.lateralJoin(expand(F.col("text").outer())).select("qid", "place", "s", "p", "o")


def worker_local_join(a: DataFrame, b: DataFrame) -> DataFrame:
    """Two modules joined on (worker, prop = src) by one process for each worker: parallel mode in its literal form. A
    worker's two modules must fit in its memory; the plan of ``run_parallel`` has no such need."""

    def join(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        out = x.merge(y, left_on="prop", right_on="src", suffixes=("", "_b"))
        return pd.DataFrame({"worker": out["worker"], "root": out["src"], "middle": out["prop"], "leaf": out["prop_b"]})

    return a.groupBy("worker").cogroup(b.groupBy("worker")).applyInPandas(join, "worker int, root string, middle string, leaf string")


def ship(spark) -> None:
    """Gives the executors this package, for functions that import it there."""
    import os
    import tempfile
    import zipfile

    import triplefed

    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    package = os.path.dirname(os.path.abspath(triplefed.__file__))
    out = os.path.join(tempfile.mkdtemp(prefix="triplefed-lib-"), "triplefed_lib.zip")
    with zipfile.ZipFile(out, "w") as z:
        for at, _, names in os.walk(package):
            for name in names:
                if name.endswith(".py"):
                    z.write(os.path.join(at, name), os.path.relpath(os.path.join(at, name), os.path.dirname(package)))
    spark.sparkContext.addPyFile(out)
    _shipped.add(app)


_shipped: set[str] = set()
