"""URL filters: host and path rules, then a weighted vocabulary.

Rules are plain column expressions, the longest that fits wins.  URLs without a rule are
judged by their terms: an Aho-Corasick automaton finds all terms in one pass over the URL,
hits count only between neighbours that are neither letters nor digits of any script, and a URL
is rejected for one strict term or for several distinct soft terms whose weights reach ``SOFT_LIMIT``.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import ahocorasick
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nearcohort.plans.runtime import ship

#: The vocabulary by topic, chosen for this engine.  A strict term names what a site
#: of the topic sells; a soft term is also used elsewhere and weighs 1.5 where its topic has strict
#: terms of its own, 1.0 where it is only bait.  Larger lists come as a table.
STRICT = ("casino", "porn", "xxx", "viagra", "escort", "warez", "jackpot", "phishing")
SOFT = {"poker": 1.5, "bets": 1.5, "bet": 1.5, "adult": 1.5, "dating": 1.5, "pills": 1.5, "torrent": 1.5, "crack": 1.5,
        "cheap": 1.0, "free": 1.0, "win": 1.0, "ads": 1.0, "track": 1.0, "loan": 1.0, "click": 1.0}
SOFT_LIMIT = 2.0
#: Terms of a vocabulary table: the automaton travels with every task.
MAX_TERMS = 1_000_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class UrlRule:
    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path


#: The rules that the query applies.
RULES = (UrlRule("allow", "org", "/"), UrlRule("block", "example.org", "/es/"), UrlRule("block", "example.org", "/en/1"),
         UrlRule("allow", "com", "/fr/"), UrlRule("block", "com", "/de/"))


def lower_ascii(c: Column) -> Column:
    return F.translate(c, UPPER, LOWER)


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Both empty for null and for urls without ``://``."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substr(rest, F.length(host) + 1), r"^[^?#]*", 0)
    return lower_ascii(host), path


def first_rule(host: Column, path: Column, rules: Sequence[UrlRule]) -> tuple[Column, Column]:
    """Name and verdict of the longest rule that fits, null without one."""
    name = verdict = F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: len(r.name)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        name = F.when(fits, F.lit(r.name)).otherwise(name)
        verdict = F.when(fits, F.lit(r.verdict)).otherwise(verdict)
    return name, verdict


_LOW = str.maketrans(UPPER, LOWER)


class TermScanner:
    """Counts strict and distinct soft terms of a URL; a term that is both is strict."""

    def __init__(self, strict: Sequence[str], soft: dict[str, float]):
        self.machine = ahocorasick.Automaton()
        for t, w in ({t: w for t, w in soft.items()} | dict.fromkeys(strict)).items():
            if t:
                self.machine.add_word(t.translate(_LOW), (t.translate(_LOW), w))
        if len(self.machine):
            self.machine.make_automaton()

    def scan(self, url: str | None) -> tuple[int, int, float]:
        """(distinct strict terms, distinct soft terms, weight of the soft terms)."""
        s = (url or "").translate(_LOW)
        found: dict[str, float | None] = {}
        if not len(self.machine):
            return 0, 0, 0.0
        for end, (term, w) in self.machine.iter(s):
            start = end - len(term) + 1
            if not s[start - 1:start].isalnum() and not s[end + 1:end + 2].isalnum():
                found[term] = w
        soft = [w for w in found.values() if w is not None]
        return len(found) - len(soft), len(soft), float(sum(soft))


def _scan(batches, strict, soft):
    tool = TermScanner(strict, soft)
    for b in batches:
        got = [tool.scan(u.as_py()) for u in b.column("url")]
        cols = list(zip(*got, strict=True)) if got else [[], [], []]
        yield pa.RecordBatch.from_arrays(
            [b.column("page_id"), b.column("url"), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()),
             pa.array(cols[2], pa.float64())], ["page_id", "url", "n_strict", "n_soft", "soft_weight"])


def judge(pages: DataFrame, rules: Sequence[UrlRule] = RULES, strict: Sequence[str] = STRICT,
          soft: dict[str, float] | None = None, limit: float = SOFT_LIMIT, vocabulary: DataFrame | None = None) -> DataFrame:
    """``page_id, host, path, rule, verdict, n_strict, n_soft, soft_weight`` of every url.

    ``vocabulary``, a table ``term, weight`` (null weight: strict), replaces ``strict`` and ``soft``.
    A null or empty url has empty host and path, fits no rule and is allowed.  Repeated rows and
    ids and null ids give rows of their own; other columns, whatever their names, are ignored; an
    empty table gives an empty result.
    """
    ship(pages.sparkSession)
    if vocabulary is not None:
        terms = vocabulary.select("term", F.col("weight").cast("double")).where("term is not null").distinct().limit(MAX_TERMS + 1).collect()
        if len(terms) > MAX_TERMS:
            raise ValueError(f"more than {MAX_TERMS} terms")
        strict, soft = [t for t, w in terms if w is None], {t: w for t, w in sorted(terms, key=lambda x: (x[0], x[1] or 0.0)) if w is not None}
    soft = SOFT if soft is None else soft
    strict = tuple(strict)
    got = (pages.select(F.col("page_id").cast("long").alias("page_id"), "url")
           .mapInArrow(lambda it: _scan(it, strict, soft),
                       "page_id long, url string, n_strict long, n_soft long, soft_weight double"))
    host, path = host_and_path(F.col("url"))
    got = got.withColumn("host", host).withColumn("path", path)
    name, verdict = first_rule(F.col("host"), F.col("path"), rules)
    bad = (F.col("n_strict") > 0) | ((F.col("n_soft") > 1) & (F.col("soft_weight") >= limit))
    return got.select("page_id", "host", "path", name.alias("rule"),
                      F.coalesce(verdict, F.when(bad, "block").otherwise("allow")).alias("verdict"),
                      "n_strict", "n_soft", "soft_weight")


def judge_sql(rules: Sequence[UrlRule] = RULES, strict: Sequence[str] = STRICT, soft: dict[str, float] | None = None,
              limit: float = SOFT_LIMIT) -> str:
    """The same in DuckDB SQL, for the oracle."""
    soft = SOFT if soft is None else soft
    low = f"translate(coalesce(url, ''), '{UPPER}', '{LOWER}')"
    hit = lambda t: f"CAST(regexp_matches(u, '(^|[^\\p{{L}}\\p{{N}}]){t}([^\\p{{L}}\\p{{N}}]|$)') AS INT)"
    cases = {"rule": "NULL", "verdict": "NULL"}
    for r in sorted(rules, key=lambda r: len(r.name)):
        fits = f"(host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}')"
        cases = {"rule": f"CASE WHEN {fits} THEN '{r.name}' ELSE {cases['rule']} END",
                 "verdict": f"CASE WHEN {fits} THEN '{r.verdict}' ELSE {cases['verdict']} END"}
    return f"""
WITH a AS (SELECT page_id, {low} AS u,
                  CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
b AS (SELECT page_id, u, rest, regexp_extract(rest, '^[^/?#]*') AS h FROM a),
c AS (SELECT page_id, u, translate(h, '{UPPER}', '{LOWER}') AS host,
             regexp_extract(substr(rest, length(h) + 1), '^[^?#]*') AS path FROM b),
d AS (SELECT *, CAST({' + '.join(map(hit, strict))} AS BIGINT) AS n_strict,
             CAST({' + '.join(map(hit, soft))} AS BIGINT) AS n_soft,
             CAST({' + '.join(f'{w} * {hit(t)}' for t, w in soft.items())} AS DOUBLE) AS soft_weight FROM c)
SELECT page_id, host, path, {cases['rule']} AS rule,
       coalesce({cases['verdict']}, CASE WHEN n_strict > 0 OR (n_soft > 1 AND soft_weight >= {limit}) THEN 'block' ELSE 'allow' END) AS verdict,
       n_strict, n_soft, soft_weight FROM d"""
