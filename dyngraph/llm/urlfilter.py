"""URL filters: longest-prefix rules, then naive Bayes over the words of segmented hosts and paths.

Concatenated host names are split into words by a unigram Viterbi search; the words, those of the path and the host's
suffix are scored by a multinomial naive Bayes. The unigram counts cover the text of every page. No dictionary is
broadcast: each distinct host gets the words that stand in it by a join of its substrings with the counted words, is split
once, and its words are joined back to its urls. The classes are fitted on at most ``max_fitted`` urls that a rule judges
(labelled rows), chosen by a hash of page_id. Every url is then judged: by the longest rule that fits, else by the classifier.

Results for odd input: a null url, or one without ``://``, has an empty host and path, fits no rule and is judged by
the prior; ties of rules go to the one named last among equals in length, ties of classes to allow; without judged
urls everything is allowed; repeated rows are judged each; an empty table gives no rows; very long urls are judged
whole; words of more than ``LONGEST_WORD`` letters are no dictionary words; further columns are left alone.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

# The rules of the contract, (host/path prefix, verdict).
RULES = (("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block"), ("net/fr/", "block"))
#: Labelled urls that the classifier is fitted on at most.
MAX_FITTED = 20_000
#: Letters of a dictionary word at most.
LONGEST_WORD = 24
#: Parts that the rows of one host, or of one word of many hosts, are dealt over.
SALTS = 16
SMOOTHING = 1.0
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_PIECE = r"\p{L}+|\p{Nd}+"


def host_of(url: Column) -> Column:
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(rest, _UPPER, _UPPER.lower())


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column, rules: tuple = RULES) -> Column:
    """The longest fitting rule's text, or null."""
    out = F.lit(None).cast("string")
    for text, _ in sorted(rules, key=lambda x: len(x[0])):  # the longest is tested last and so wins
        domain, slash, rest = text.partition("/")
        fits = ((host == domain) | host.endswith("." + domain)) & path.startswith(slash + rest)
        out = F.when(fits, F.lit(text)).otherwise(out)
    return out


def split(name: str, log_rate: dict[str, float], unknown: float) -> list[str]:
    """Most likely words of ``name``: Viterbi over prefixes, unknown words paying for each letter."""
    best, back = [0.0], [0]
    for end in range(1, len(name) + 1):
        top, at = -math.inf, end - 1
        for begin in range(max(0, end - LONGEST_WORD), end):
            word = name[begin:end]
            score = best[begin] + log_rate.get(word, unknown * (1 + len(word)))
            if score > top:
                top, at = score, begin
        best.append(top)
        back.append(at)
    out, end = [], len(name)
    while end:
        out.append(name[back[end] : end])
        end = back[end]
    return out[::-1]


def pieces_of(host: Column) -> tuple[Column, Column]:
    """The host's last label, and the runs of letters or of digits of its other labels, in order."""
    labels = F.filter(F.split(host, r"\."), lambda x: x != "")
    pieces = F.transform(F.slice(labels, F.lit(1), F.greatest(F.size(labels) - 1, F.lit(0))), lambda x: F.regexp_extract_all(x, F.lit(_PIECE), F.lit(0)))
    return F.get(labels, F.size(labels) - 1), F.flatten(pieces)


def path_words(path: Column) -> Column:
    """Words of the path (``p:``), numbers as one word."""
    return F.transform(F.regexp_extract_all(F.lower(path), F.lit(_PIECE), F.lit(0)), lambda x: F.when(x.rlike(r"^\p{Nd}"), F.lit("p:#")).otherwise(F.concat(F.lit("p:"), x)))


def word_counts(pages: DataFrame) -> DataFrame:
    """(w, n): how often each word of up to ``LONGEST_WORD`` letters stands in the text of all pages."""
    text = F.lower(F.regexp_replace(F.coalesce("html", F.lit("")), r"(?s)<(script|style)\b.*?</\1>|<[^>]*>|&\w+;", " "))
    words = pages.select(F.explode(F.regexp_extract_all(text, F.lit(r"\p{L}+"), F.lit(0))).alias("w"))
    return words.filter(F.length("w") <= LONGEST_WORD).groupBy("w").agg(F.count(F.lit(1)).alias("n"))


def segmented(parts: DataFrame, counts: DataFrame) -> DataFrame:
    """(host, words): each distinct host with its last label (``s:``) and the words that its pieces split into (``h:``).

    A host meets its candidate words by a hash of its name; hosts of equal hash would share candidates, which changes
    nothing, since only substrings of the host are looked up.
    """
    suffix, pieces = pieces_of(F.col("host"))
    hosts = parts.select("host").distinct().select("host", F.xxhash64("host").alias("hid"), suffix.alias("suffix"), pieces.alias("pieces"))
    hosts = written(hosts, "hosts")
    counts = written(counts, "words")
    total = counts.agg((F.coalesce(F.sum("n"), F.lit(0)) + 1.0).alias("t")).first()["t"]
    ends = F.sequence(F.lit(1), F.length("piece"))
    cuts = F.flatten(F.transform(ends, lambda e: F.transform(F.sequence(F.greatest(e - LONGEST_WORD, F.lit(0)), e - 1), lambda b: F.substring(F.col("piece"), b + 1, e - b))))
    subs = hosts.select("hid", F.explode("pieces").alias("piece")).select("hid", F.explode(cuts).alias("w"))
    known = written(counts.join(subs.select("w").distinct(), "w"), "known")  # words that stand in some host
    salt = F.pmod("hid", F.lit(SALTS)).cast("int").alias("salt")
    dealt = known.select("w", "n", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    found = subs.select("hid", "w", salt).join(dealt, ["w", "salt"]).groupBy("hid").agg(F.collect_set(F.struct("w", "n")).alias("found"))
    unknown = math.log(1 / total)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, suffixes, pieces, found = (batch.column(c).to_pylist() for c in ("host", "suffix", "pieces", "found"))
            out = []
            for last, runs, near in zip(suffixes, pieces, found, strict=True):
                rate = {x["w"]: math.log(x["n"] / total) for x in near or ()}
                out.append([f"s:{last}"] * (last is not None) + [f"h:{w}" for run in runs for w in split(run, rate, unknown)])
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(out, pa.list_(pa.string()))], names=["host", "words"])

    met = hosts.join(found, "hid", "left").select("host", "suffix", "pieces", "found")
    return written(met.mapInArrow(work, "host string, words array<string>"), "segmented")


def parts_of(pages: DataFrame, rules: tuple = RULES) -> DataFrame:
    """page_id, host, path and rule of every url."""
    parts = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    return parts.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules))


def worded(parts: DataFrame, hosts: DataFrame) -> DataFrame:
    """``parts`` with the words of host and path; urls of one host are dealt over ``SALTS`` parts."""
    dealt = hosts.select("host", F.col("words").alias("of_host"), F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    url = parts.withColumn("salt", F.pmod(F.xxhash64("page_id", "path"), F.lit(SALTS)).cast("int"))
    return url.join(dealt, ["host", "salt"]).select("page_id", "host", "path", "rule", F.concat("of_host", path_words(F.col("path"))).alias("words"))


@dataclass(frozen=True)
class Model:
    """The fitted classes; as large as the words of at most ``max_fitted`` urls, so it travels with the task."""

    prior: float
    weights: dict[str, float]

    def odds(self, words: list[str]) -> float:
        """Log odds of block against allow; words that no fitted url has say nothing."""
        return self.prior + sum(self.weights.get(w, 0.0) for w in words)


def fit(urls: DataFrame, rules: tuple = RULES, max_fitted: int = MAX_FITTED) -> Model:
    """The classes from at most ``max_fitted`` of those rows of ``worded`` that a rule judges."""
    block = [text for text, verdict in rules if verdict == "block"]
    judged = urls.filter("rule is not null").orderBy(F.xxhash64("page_id"), "page_id", "host", "path").limit(max_fitted)
    each = judged.select(F.col("rule").isin(block).alias("bad"), F.explode(F.concat("words", F.array(F.lit("")))).alias("w"))  # the empty word counts urls
    rows = each.groupBy("w").agg(F.count_if("bad").alias("block"), F.count_if(~F.col("bad")).alias("allow")).collect()
    seen = {k: {r["w"]: r[k] for r in rows if r[k]} for k in ("block", "allow")}
    docs = {k: c.pop("", 0) for k, c in seen.items()}
    if not rows:
        return Model(-math.inf, {})
    known = set(seen["allow"]) | set(seen["block"])
    size = {k: math.log(sum(c.values()) + SMOOTHING * len(known)) for k, c in seen.items()}
    rate = lambda k, n: math.log(n + SMOOTHING) - size[k]
    weights = {w: rate("block", seen["block"].get(w, 0)) - rate("allow", seen["allow"].get(w, 0)) for w in known}
    return Model(math.log(docs["block"] + 1) - math.log(docs["allow"] + 1), weights)


def classify(urls: DataFrame, fitted: Model, rules: tuple = RULES) -> DataFrame:
    """Rows of ``worded`` with ``said`` and ``odds`` (the method's verdict) and ``verdict`` (the rule's, else the method's)."""
    model = urls.sparkSession.sparkContext.broadcast(fitted)
    says = dict(rules)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            odds = [model.value.odds(w) for w in batch.column("words").to_pylist()]
            said = ["block" if o > 0 else "allow" for o in odds]
            verdict = [says[r] if r else s for r, s in zip(batch.column("rule").to_pylist(), said, strict=True)]
            extra = [pa.array(verdict, pa.string()), pa.array(said, pa.string()), pa.array([round(o, 6) for o in odds], pa.float64())]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("page_id", "host", "path", "rule", "words")), *extra], names=["page_id", "host", "path", "rule", "words", "verdict", "said", "odds"])

    return urls.mapInArrow(work, "page_id long, host string, path string, rule string, words array<string>, verdict string, said string, odds double")


def judge(pages: DataFrame, rules: tuple = RULES, max_fitted: int = MAX_FITTED) -> DataFrame:
    """One row per row of ``pages`` (page_id, url, html): page_id, host, path, rule, words, verdict, said, odds."""
    parts = parts_of(pages, rules)
    urls = worded(parts, segmented(parts, word_counts(pages)))
    return classify(urls, fit(urls, rules, max_fitted), rules)
