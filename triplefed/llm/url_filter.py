"""URL filter: host and path rules first, then a weighted vocabulary matched by an Aho-Corasick automaton.

A url that no rule decides is judged by its terms. All terms are found in one pass over the lower-cased url; a hit
counts only where no ASCII letter or digit touches it on either side. One distinct strict hit rejects the url, and so do
soft hits of at least ``soft_distinct`` different terms whose weights reach ``soft_limit``; one soft term alone never does.

The vocabulary (``vocabulary.py``, or any lines of that form) is general knowledge: a term, its weight or ``strict``, and how
it is inflected. It isn't drawn from any table.

Defined cases: a null url, or one without ``://``, has an empty host and path, fits no rule and keeps verdict
``allow`` unless its text holds rejecting terms (null has none). Repeated rows are judged each on its own; columns
that are not asked for are never read, so further columns with any names do no harm. Empty tables give no rows. A url of any
length is scanned once.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.llm.common import LOWER, UPPER, ascii_lower, ship, table
from triplefed.llm.vocabulary import VOCABULARY

SOFT_LIMIT, SOFT_DISTINCT = 2, 2


def inflected(term: str, forms: str) -> list[str]:
    """A term and what its forms make of it: ``s`` a plural, ``ing`` and ``er`` those of a verb (its last letter doubled
    where the form says so: ``2ing``), ``-`` parts written together as well as apart."""
    out = [term]
    for form in forms.split(",") if forms else []:
        if form == "-":
            out += [term.replace("-", "")]
        elif form.startswith("2"):
            out.append(term + term[-1] + form[1:])
        else:
            out.append(term[:-1] + form if form in ("ing", "er", "ers") and term.endswith("e") else term + form)
    return out


def read_vocabulary(lines: list[str]) -> tuple[tuple[str, ...], dict[str, int]]:
    """Strict terms, and soft ones with their weights, of lines ``weight term[,forms]``; a line that begins with # is a remark."""
    strict: dict[str, None] = {}
    soft: dict[str, int] = {}
    for line in lines:
        if not line.strip() or line.startswith("#"):
            continue
        weight, _, rest = line.strip().partition(" ")
        for entry in rest.split():
            term, _, forms = entry.partition(",")
            for form in inflected(term, forms):
                if weight == "strict":
                    strict[form] = None
                else:
                    soft[form] = int(weight)
    return tuple(strict), {k: v for k, v in soft.items() if k not in strict}


STRICT, SOFT = read_vocabulary(VOCABULARY.splitlines())


@dataclass(frozen=True)
class Rule:
    """``place`` is a host, a slash and the start of a path, such as ``example.org/es/``."""

    place: str
    verdict: str

    @property
    def host(self) -> str:
        return self.place.split("/", 1)[0]

    @property
    def path(self) -> str:
        return self.place[len(self.host):]


#: The rule set of the production query.
RULES = (
    Rule("org/", "allow"),
    Rule("example.org/es/", "block"),
    Rule("example.org/en/1", "block"),
    Rule("com/fr/", "allow"),
    Rule("com/de/", "block"),
)


def host_column(url: str = "url"):
    return F.coalesce(ascii_lower(F.regexp_extract(F.col(url), r"(?s)^.*?://([^/?#]*)", 1)), F.lit(""))


def path_column(url: str = "url"):
    return F.coalesce(F.regexp_extract(F.col(url), r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


class Judge:
    """Rules by host and an automaton for the terms; built once in each task."""

    def __init__(self, rules: tuple[Rule, ...], strict: tuple[str, ...], soft: dict[str, int], soft_limit: int, soft_distinct: int = SOFT_DISTINCT):
        import ahocorasick

        self.by_host: dict[str, list[Rule]] = {}
        for rule in sorted(rules, key=lambda r: (-len(r.place), r.place)):
            self.by_host.setdefault(rule.host, []).append(rule)
        self.soft, self.soft_limit, self.soft_distinct = soft, soft_limit, soft_distinct
        hard = set(strict)
        self.terms = ahocorasick.Automaton()
        for term in {*strict, *soft}:
            self.terms.add_word(term, (term, term in hard))
        self.terms.make_automaton()

    def rule(self, host: str, path: str) -> Rule | None:
        best, at = None, host
        while True:
            for rule in self.by_host.get(at, ()):
                if path.startswith(rule.path):
                    if best is None or len(rule.place) > len(best.place):
                        best = rule
                    break
            dot = at.find(".")
            if dot < 0:
                return best
            at = at[dot + 1:]

    def hits(self, url: str) -> tuple[set[str], set[str]]:
        strict, soft = set(), set()
        for end, (term, is_strict) in self.terms.iter(url):
            begin = end - len(term) + 1
            if (begin and _joins(url[begin - 1])) or (end + 1 < len(url) and _joins(url[end + 1])):
                continue
            (strict if is_strict else soft).add(term)
        return strict, soft

    def rejects(self, strict: set[str], soft: set[str]) -> bool:
        return bool(strict) or (len(soft) >= self.soft_distinct and sum(self.soft[x] for x in soft) >= self.soft_limit)


def _joins(c: str) -> bool:
    return "a" <= c <= "z" or "0" <= c <= "9"


_TABLE = str.maketrans(UPPER, LOWER)


def filter_urls(
    pages: DataFrame,
    key: str = "page_id",
    url: str = "url",
    rules: tuple[Rule, ...] = RULES,
    strict: tuple[str, ...] = STRICT,
    soft: dict[str, int] = SOFT,
    soft_limit: int = SOFT_LIMIT,
    soft_distinct: int = SOFT_DISTINCT,
) -> DataFrame:
    """Per row: key, host, path, rule, verdict, n_strict, n_soft (distinct terms) and soft_weight. No shuffle."""
    ship(pages.sparkSession)
    parsed = pages.select(F.col(key).alias("__key"), F.col(url).alias("__url"), host_column(url).alias("host"), path_column(url).alias("path"))
    schema = f"{key} {pages.schema[key].dataType.simpleString()}, host string, path string, rule string, verdict string, n_strict int, n_soft int, soft_weight int"

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        j = Judge(rules, strict, soft, soft_limit, soft_distinct)
        for batch in batches:
            hosts, paths = batch["host"].to_pylist(), batch["path"].to_pylist()
            rows = []
            for text, host, path in zip(batch["__url"].to_pylist(), hosts, paths, strict=True):
                hard, mild = j.hits((text or "").translate(_TABLE))
                rule = j.rule(host, path) if host else None
                verdict = rule.verdict if rule else "block" if j.rejects(hard, mild) else "allow"
                rows.append((rule.place if rule else None, verdict, len(hard), len(mild), sum(j.soft[x] for x in mild)))
            rule_, verdict_, hard_, mild_, weight_ = zip(*rows) if rows else ((),) * 5
            yield pa.RecordBatch.from_arrays(
                [batch["__key"], batch["host"], batch["path"], pa.array(rule_, pa.string()), pa.array(verdict_, pa.string()), pa.array(hard_, pa.int32()), pa.array(mild_, pa.int32()), pa.array(weight_, pa.int32())],
                names=[key, "host", "path", "rule", "verdict", "n_strict", "n_soft", "soft_weight"],
            )

    return parsed.mapInArrow(judge, schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(table(spark, sf_dir, "pages"))


def _oracle() -> str:
    """A url cut at whatever is no letter or digit: a term stands in it where its own parts stand in a row."""

    def fits(rule: Rule) -> str:
        return f"((host = '{rule.host}' OR ends_with(host, '.{rule.host}')) AND starts_with(path, '{rule.path}'))"

    ordered = sorted(RULES, key=lambda r: -len(r.place))
    named = " ".join(f"WHEN {fits(r)} THEN '{r.place}'" for r in ordered)
    decided = " ".join(f"WHEN {fits(r)} THEN '{r.verdict}'" for r in ordered)
    terms = ", ".join([f"('{t}', 0)" for t in STRICT] + [f"('{t}', {w})" for t, w in SOFT.items()])
    return f"""
    WITH p AS (
        SELECT page_id, row_number() OVER () AS k, translate(coalesce(url, ''), '{UPPER}', '{LOWER}') AS u,
               coalesce(translate(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), '{UPPER}', '{LOWER}'), '') AS host,
               coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') AS path
        FROM pages),
    t(term, weight) AS (VALUES {terms}),
    f AS (SELECT k, weight FROM p JOIN t ON contains(u, term) AND regexp_matches(u, '(^|[^a-z0-9])' || regexp_escape(term) || '([^a-z0-9]|$)')),
    c AS (SELECT k, count(*) FILTER (weight = 0) AS n_strict, count(*) FILTER (weight > 0) AS n_soft, sum(weight) AS soft_weight FROM f GROUP BY k),
    h AS (SELECT p.*, coalesce(n_strict, 0) AS n_strict, coalesce(n_soft, 0) AS n_soft, coalesce(soft_weight, 0) AS soft_weight FROM p LEFT JOIN c USING (k))
    SELECT page_id, host, path, CASE {named} END AS rule,
           CASE {decided} WHEN n_strict > 0 OR (n_soft >= {SOFT_DISTINCT} AND soft_weight >= {SOFT_LIMIT}) THEN 'block' ELSE 'allow' END AS verdict,
           CAST(n_strict AS INT) AS n_strict, CAST(n_soft AS INT) AS n_soft, CAST(soft_weight AS INT) AS soft_weight
    FROM h"""


ORACLE = _oracle()
