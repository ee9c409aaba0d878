"""URL filtering: host and path rules first, then a weighted vocabulary.

One automaton finds all terms of the vocabulary in a URL. A hit counts if it
stands alone, between characters that are neither letters nor digits. One
strict term rejects a URL; soft terms reject it only together, each counted
once however often it comes.
"""

from __future__ import annotations

from dataclasses import dataclass

import ahocorasick
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cityweave.llm.kernel import mapped

# Fixed values: (verdict, rule) with host and path of each rule.
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))

# The vocabulary where no table of terms is given.
STRICT = ("adult", "casino", "escort", "hentai", "nude", "phishing", "poker", "porn", "sex", "spam", "viagra", "warez", "xxx")
SOFT = ("ads", "bet", "bets", "bonus", "cam", "cheap", "click", "crack", "farm", "free", "gambling", "hot", "loan", "lottery", "pills", "popup", "slots", "torrent", "track", "win")

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host(url: Column) -> Column:
    """What stands between the first :// and the next /, ? or #, with A-Z in lower case."""
    return F.translate(F.coalesce(F.regexp_extract(url, r"://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule(host_: Column, path_: Column, rules=RULES) -> Column:
    """(verdict, rule) of the longest rule that fits host or a parent domain, and path; null without one."""
    out = F.lit(None).cast("struct<verdict:string,rule:string>")
    for verdict, text in sorted(rules, key=lambda r: len(r[1])):
        domain, _, start = text.partition("/")
        fits = ((host_ == domain) | F.endswith(host_, F.lit("." + domain))) & F.startswith(path_, F.lit("/" + start))
        out = F.when(fits, F.struct(F.lit(verdict).alias("verdict"), F.lit(text).alias("rule"))).otherwise(out)
    return out


@dataclass(frozen=True)
class Vocabulary:
    strict: tuple[str, ...] = STRICT
    soft: tuple[str, ...] = SOFT
    #: distinct soft terms that reject together
    several: int = 2

    @classmethod
    def of(cls, table: DataFrame, several: int = 2, bound: int = 2_000_000) -> Vocabulary:
        """From a table of (term, kind), kind being `strict` or `soft`; terms are lower-cased, and one of both kinds is strict.

        The terms go to every worker, so a table of over `bound` terms is refused.
        """
        rows = table.where("term is not null and term <> ''").select(F.lower("term").alias("term"), F.lower("kind").alias("kind")).distinct()
        if rows.count() > bound:
            raise ValueError(f"more than {bound} terms")
        by: dict[str, set[str]] = {"strict": set(), "soft": set()}
        for r in rows.collect():
            if r.kind not in by:
                raise ValueError(f"unknown kind {r.kind!r}")
            by[r.kind].add(r.term)
        return cls(tuple(sorted(by["strict"])), tuple(sorted(by["soft"] - by["strict"])), several)

    def automaton(self) -> ahocorasick.Automaton:
        out = ahocorasick.Automaton()
        for kind, terms in enumerate((self.soft, self.strict)):
            for term in terms:
                out.add_word(term, (term, kind))
        out.make_automaton()
        return out


def hits(automaton, text: str) -> tuple[int, int]:
    """Distinct strict and soft terms that stand alone in a lower-case text."""
    found: tuple[set, set] = (set(), set())
    for end, (term, kind) in automaton.iter(text):
        before, after = end - len(term), end + 1
        if (before < 0 or not _word(text[before])) and (after >= len(text) or not _word(text[after])):
            found[kind].add(term)
    return len(found[1]), len(found[0])


def _word(c: str) -> bool:
    return "a" <= c <= "z" or "0" <= c <= "9"


def judged(pages: DataFrame, vocabulary: Vocabulary = Vocabulary(), rules=RULES) -> DataFrame:
    """(page_id, host, path, rule, verdict, n_strict, n_soft) for each row of pages.

    Null urls and urls without :// have empty host and path, fit no rule and
    are judged by their text. Only page_id and url are read.
    """

    def run(batches):
        automaton = vocabulary.automaton() if vocabulary.strict or vocabulary.soft else None
        for batch in batches:
            found = [hits(automaton, (u or "").translate(_FOLD)) if automaton else (0, 0) for u in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], ["page_id", "url", "n_strict", "n_soft"])

    found = mapped(pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url")), run, "page_id long, url string, n_strict long, n_soft long")
    parts = found.withColumns({"host": host(F.col("url")), "path": path(F.col("url"))}).withColumn("r", rule(F.col("host"), F.col("path"), rules))
    own = F.when((F.col("n_strict") > 0) | (F.col("n_soft") >= vocabulary.several), "block").otherwise("allow")
    return parts.select("page_id", "host", "path", F.col("r.rule").alias("rule"), F.coalesce("r.verdict", own).alias("verdict"), "n_strict", "n_soft")


_FOLD = str.maketrans(UPPER, LOWER)


def oracle_sql(vocabulary: Vocabulary = Vocabulary(), rules=RULES) -> str:
    """The same judgement as SQL: one pattern for each term."""
    alone = lambda term: f"regexp_matches(low, '(^|[^a-z0-9]){term}([^a-z0-9]|$)')::int"
    fits = lambda text: (lambda d, s: f"((host = '{d}' or ends_with(host, '.{d}')) and starts_with(path, '/{s}'))")(*text.split("/", 1))
    ordered = sorted(rules, key=lambda r: -len(r[1]))
    pick = lambda k: "case " + " ".join(f"when {fits(r[1])} then '{r[k]}'" for r in ordered) + " end"
    return f"""
with parts as (
  select page_id, translate(coalesce(url, ''), '{UPPER}', '{LOWER}') as low,
         translate(regexp_extract(coalesce(url, ''), '://([^/?#]*)', 1), '{UPPER}', '{LOWER}') as host,
         regexp_extract(coalesce(url, ''), '://[^/?#]*([^?#]*)', 1) as path
  from pages
), counted as (
  select *, cast({" + ".join(map(alone, vocabulary.strict))} as bigint) as n_strict, cast({" + ".join(map(alone, vocabulary.soft))} as bigint) as n_soft
  from parts
)
select page_id, host, path, {pick(1)} as rule,
       coalesce({pick(0)}, case when n_strict > 0 or n_soft >= {vocabulary.several} then 'block' else 'allow' end) as verdict,
       n_strict, n_soft
from counted"""
