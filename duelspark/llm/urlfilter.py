"""URL filtering by host rules and by a weighted vocabulary.

A url's verdict is that of the longest rule that fits it. Where none fits, an Aho-Corasick automaton finds the vocabulary's
terms in the lower-cased url; a hit counts if no ASCII letter or digit touches it. One strict term, or `soft_needed`
distinct soft terms, block the url.

Defined results: a null url, or one without `://`, has an empty host and path, fits no rule, and is allowed unless its text
(if any) holds terms. Repeated terms count once. An empty table gives an empty result. Other columns of the input are left out.
"""

from __future__ import annotations

import re
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# fixed values: the rules (host and path prefix) and what each does
RULES = (("net/", "block"), ("example.net/en/", "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"))
STRICT = ("spam-farm", "porn", "xxx", "malware", "phishing", "warez", "escort")
SOFT = ("spam", "farm", "casino", "betting", "jackpot", "viagra", "cheap", "free", "winner", "adult", "torrent", "crack", "loan", "replica")

_ASCII_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
_PARTS = re.compile(r"://([^/?#]*)([^?#]*)")
_WORD = frozenset("abcdefghijklmnopqrstuvwxyz0123456789")
SCHEMA = "page_id long, host string, path string, rule string, verdict string, strict_hits int, soft_hits int"


@dataclass(frozen=True)
class Vocabulary:
    """Terms and their weights: a strict term alone reaches `soft_needed`, a soft one weighs 1."""

    strict: Sequence[str] = STRICT
    soft: Sequence[str] = SOFT
    soft_needed: int = 2

    def automaton(self) -> ahocorasick.Automaton:
        found = ahocorasick.Automaton()
        for weight, terms in ((1, self.soft), (self.soft_needed, self.strict)):
            for term in terms:
                found.add_word(term, (term, weight))
        found.make_automaton()
        return found


def split_url(url: str | None) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path; both empty without `://`."""
    parts = _PARTS.search(url or "")
    return (parts[1].translate(_ASCII_LOWER), parts[2]) if parts else ("", "")


def fitting_rule(host: str, path: str, rules: Sequence[tuple[str, str]]) -> tuple[str, str] | None:
    """The longest rule whose host is this host or a parent of it, and whose path the path starts with."""
    best = None
    for rule, verdict in rules:
        cut = rule.index("/")
        if (host == rule[:cut] or host.endswith("." + rule[:cut])) and path.startswith(rule[cut:]):
            if best is None or len(rule) > len(best[0]):
                best = (rule, verdict)
    return best


def term_hits(url: str, automaton: ahocorasick.Automaton) -> dict[str, int]:
    """Distinct terms that stand between boundaries, with their weights."""
    text, hits = url.translate(_ASCII_LOWER), {}
    for end, (term, weight) in automaton.iter(text):
        start = end - len(term) + 1
        if (start == 0 or text[start - 1] not in _WORD) and (end + 1 == len(text) or text[end + 1] not in _WORD):
            hits[term] = weight
    return hits


def judge_urls(pages: DataFrame, rules: Sequence[tuple[str, str]] = RULES, vocabulary: Vocabulary = Vocabulary()) -> DataFrame:
    """One row per page: page_id, host, path, rule, verdict, strict_hits, soft_hits."""
    rules = tuple(rules)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton, strict = vocabulary.automaton(), set(vocabulary.strict)
        for batch in batches:
            rows: list[list] = [[] for _ in range(6)]
            for url in batch.column(1).to_pylist():
                host, path = split_url(url)
                hits = term_hits(url or "", automaton)
                rule = fitting_rule(host, path, rules)
                verdict = rule[1] if rule else "block" if sum(hits.values()) >= vocabulary.soft_needed else "allow"
                n_strict = sum(t in strict for t in hits)
                for column, value in zip(rows, (host, path, rule and rule[0], verdict, n_strict, len(hits) - n_strict), strict=True):
                    column.append(value)
            kinds = [pa.string()] * 4 + [pa.int32()] * 2
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(v, k) for v, k in zip(rows, kinds, strict=True))], names=[x.split()[0] for x in SCHEMA.split(", ")])

    return pages.select(F.col("page_id").cast("long"), F.col("url").cast("string")).mapInArrow(judge, SCHEMA)


def oracle(rules: Sequence[tuple[str, str]] = RULES, vocabulary: Vocabulary = Vocabulary()) -> str:
    """The same as DuckDB SQL."""
    lower = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    fits = [
        f"WHEN (host = '{r[: r.index('/')]}' OR ends_with(host, '.{r[: r.index('/')]}')) AND starts_with(path, '{r[r.index('/') :]}') THEN '{r}'"
        for r, _ in sorted(rules, key=lambda x: -len(x[0]))
    ]

    def hits(terms: Sequence[str]) -> str:
        return " + ".join(f"CAST(regexp_matches(low, '(^|[^a-z0-9]){re.escape(t)}($|[^a-z0-9])') AS INTEGER)" for t in terms)

    said = " ".join(f"WHEN rule = '{r}' THEN '{v}'" for r, v in rules)
    return f"""
WITH parts AS (
  SELECT page_id, {lower.format("coalesce(url, '')")} AS low,
         {lower.format("regexp_extract(coalesce(url, ''), '://([^/?#]*)([^?#]*)', 1)")} AS host,
         regexp_extract(coalesce(url, ''), '://([^/?#]*)([^?#]*)', 2) AS path FROM pages),
judged AS (
  SELECT page_id, host, path, CASE {" ".join(fits)} END AS rule, {hits(vocabulary.strict)} AS strict_hits, {hits(vocabulary.soft)} AS soft_hits FROM parts)
SELECT page_id, host, path, rule,
       CASE {said} WHEN strict_hits * {vocabulary.soft_needed} + soft_hits >= {vocabulary.soft_needed} THEN 'block' ELSE 'allow' END AS verdict,
       CAST(strict_hits AS INTEGER) AS strict_hits, CAST(soft_hits AS INTEGER) AS soft_hits
FROM judged"""
