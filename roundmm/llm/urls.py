"""URL filters: an Aho-Corasick pass counts strict and soft terms of a weighted vocabulary, after host rules."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import ahocorasick
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from roundmm.llm.common import ascii_lower

# Terms that reject alone; terms of which two reject; terms of which three reject. Plurals are added by rule.
STRICT = (
    "pill", "viagra", "cialis", "casino", "porn", "xxx", "spam", "malware", "phishing", "warez", "escort", "keygen", "torrent", "gambling", "jackpot", "roulette", "nude", "hentai",
)
SOFT = (
    "cheap", "free", "bonus", "win", "winner", "loan", "bet", "deal", "discount", "farm", "click", "adult", "crypto", "hack", "coupon", "poker", "slot", "payday", "prize", "giveaway", "lottery", "dating",
)
WEAK = ("ad", "track", "tracker", "promo", "offer", "banner", "sponsor", "affiliate", "sale")


def with_plurals(terms: tuple[str, ...], weight: float) -> dict[str, float]:
    """The terms, and an s behind those that have none."""
    return {t: weight for word in terms for t in ((word,) if word.endswith(("s", "x")) else (word, f"{word}s"))}


#: A url is rejected where the weights of its distinct terms reach 1.
WEIGHTS = {**with_plurals(WEAK, 0.375), **with_plurals(SOFT, 0.5), **with_plurals(STRICT, 1.0)}


@dataclass(frozen=True)
class Vocabulary:
    """Terms and weights; a term of weight 1 or more is strict, others are soft."""

    weights: dict[str, float] = field(default_factory=lambda: dict(WEIGHTS))
    reject_at: float = 1.0
    rules: tuple[tuple[str, str, str], ...] = field(
        default=(("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
    )

    @classmethod
    def of_table(cls, terms: DataFrame, most: int = 1_000_000, **options) -> Vocabulary:
        """From a table ``term, weight``, of at most ``most`` rows: the automaton stands in every worker. Terms are lower-cased in A-Z; of equal ones the greatest weight
        counts; null and empty terms, and weights of at most 0, are left out."""
        rows = terms.select(ascii_lower(F.col("term")).alias("term"), F.col("weight").cast("double").alias("weight")).where("term <> '' and weight > 0")
        found = rows.groupBy("term").agg(F.max("weight").alias("weight")).limit(most + 1).collect()  # bounded
        if len(found) > most:
            raise ValueError(f"more than {most} terms")
        return cls({r["term"]: r["weight"] for r in found}, **options)


def term_counter(vocabulary: Vocabulary):
    """A function of a lower-cased text: distinct strict and soft terms that stand between non-alphanumerics, and the sum of their weights."""
    machine = ahocorasick.Automaton()
    for t, w in vocabulary.weights.items():
        machine.add_word(t, (t, w))
    if vocabulary.weights:
        machine.make_automaton()

    def counted(text: str) -> tuple[int, int, float]:
        found = {}
        for end, (term, w) in machine.iter(text) if vocabulary.weights and text else ():
            before, after = end - len(term), end + 1
            if (before < 0 or not text[before].isalnum()) and (after >= len(text) or not text[after].isalnum()):
                found[term] = w
        strict = sum(w >= vocabulary.reject_at for w in found.values())
        return strict, len(found) - strict, float(sum(found[t] for t in sorted(found)))

    return counted


def term_counts(url: Column, vocabulary: Vocabulary) -> Column:
    @F.pandas_udf("strict int, soft int, weight double")
    def counts(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        counted = term_counter(vocabulary)
        for part in parts:
            yield pd.DataFrame([counted(x) for x in part], columns=["strict", "soft", "weight"]).astype({"strict": "int32", "soft": "int32", "weight": "float64"})

    return counts(url)


def url_host(url: Column) -> Column:
    return ascii_lower(F.regexp_extract(F.coalesce(url, F.lit("")), "(?s)^.*?://([^/?#]*)", 1))


def url_path(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), "(?s)^.*?://[^/?#]*([^?#]*)", 1)


def judged(pages: DataFrame, vocabulary: Vocabulary | None = None) -> DataFrame:
    """``page_id, host, path, rule, verdict, strict_terms, soft_terms, weight`` for every row of ``pages(page_id, url)``.

    The longest fitting rule decides; without one, distinct terms whose weights reach ``reject_at`` block: one strict term, or several soft ones.
    A null url, or one without ``://``, has empty host and path (its text is still searched for terms); repeated rows
    are judged alike; an empty table gives no rows; other columns are ignored.
    """
    v = vocabulary or Vocabulary()
    rows = pages.select("page_id", "url", url_host(F.col("url")).alias("host"), url_path(F.col("url")).alias("path"))
    rule, kind = F.lit(None).cast("string"), F.lit(None).cast("string")
    for verdict, host, path in sorted(v.rules, key=lambda r: len(r[1] + r[2])):
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(path)
        rule, kind = F.when(fits, F.lit(host + path)).otherwise(rule), F.when(fits, F.lit(verdict)).otherwise(kind)
    counts = term_counts(ascii_lower(F.coalesce("url", F.lit(""))), v)
    out = rows.select("page_id", "host", "path", rule.alias("rule"), kind.alias("_kind"), counts.alias("_terms"))
    method = F.when(F.col("_terms.weight") >= v.reject_at, "block").otherwise("allow")
    return out.select("page_id", "host", "path", "rule", F.coalesce("_kind", method).alias("verdict"), F.col("_terms.strict").alias("strict_terms"), F.col("_terms.soft").alias("soft_terms"), F.col("_terms.weight").alias("weight"))
