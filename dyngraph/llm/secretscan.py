"""Secret scans: fixed patterns, and character Markov models of random strings against identifiers (native).

Two first-order Markov models over the characters of keys and tokens are trained from a labelled sample: random
strings (hexadecimal, base-64 and base-36 digests) and ordinary identifiers (composed names, and the words of a
bounded number of documents labelled good). A long token is reported when the mean log-likelihood ratio of its
character pairs is above ``threshold``. The spans of the fixed patterns are always reported.

Results for odd input: null text is empty text and has no spans; repeated rows are scanned each; without labelled
documents the composed names alone make the identifier model; an empty table gives no rows; very long texts are
scanned whole; further columns of the input are left alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import words

# The patterns of the contract. Lower bounds on length that hold for whole runs are written into the
# pattern; the one on the value of an assignment is tested afterwards, since a failing match still takes up its text.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"(?<![0-9a-f])[0-9a-f]{24,}"
KINDS = ("assign", "access", "hex", "markov")

ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"
MIN_TOKEN = 20
TOKEN = r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{%d,}" % MIN_TOKEN
THRESHOLD = 0.3
#: Labelled documents and generated strings that the models see at most.
MAX_LABELLED = 1_000
GENERATED = 4_000
MASK = "[SECRET]"

# Parts of ordinary identifiers.
NAME_PARTS = (
    "get set is has user name file path list item count index value key map node edge graph table row column total "
    "page size time date start end first last next prev parent child root leaf left right top bottom width height "
    "color style class id type kind state status error message event handler listener request response client server "
    "config option default cache buffer stream reader writer parser token format source target input output result "
    "query update delete insert select create remove add find search sort filter group order customer account price"
).split()

_SPANS = "array<struct<s:int,e:int,v:string>>"
_CHUNK = 256


def _located(text: Column, pattern: str, group: int = 0) -> Column:
    """Every leftmost non-overlapping match as (s, e, v), in code points; v is the wanted group.

    The pieces between matches give the offsets. Spans are gathered in chunks, as appending to one array copies it.
    """
    empty = F.expr(f"cast(array() as {_SPANS})")
    parts = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("m"), F.regexp_extract_all(text, F.lit(pattern), F.lit(group)).alias("v"))
    start = F.struct(F.lit(0).alias("at"), empty.alias("part"), F.expr(f"cast(array() as array<{_SPANS}>)").alias("parts"))

    def step(a: Column, x: Column) -> Column:
        s = a["at"] + F.length(x["gap"])
        e = s + F.length(F.coalesce(x["m"], F.lit("")))
        more = F.concat(a["part"], F.array(F.struct(s.alias("s"), e.alias("e"), x["v"].alias("v"))))
        full = F.size(a["part"]) >= _CHUNK - 1
        return F.struct(
            e.alias("at"),
            F.when(full, empty).otherwise(more).alias("part"),
            F.when(full, F.concat(a["parts"], F.array(more))).otherwise(a["parts"]).alias("parts"),
        )

    found = F.aggregate(parts, start, step, lambda a: F.filter(F.flatten(F.concat(a["parts"], F.array(a["part"]))), lambda x: x["v"].isNotNull()))
    return F.when(text.rlike(pattern), found).otherwise(empty)


def labelled_sample(spark: SparkSession, docs: DataFrame, labels: DataFrame, max_labelled: int = MAX_LABELLED, generated: int = GENERATED) -> DataFrame:
    """(random, token): the training rows of both models; bounded by ``max_labelled`` documents and ``generated`` strings each."""
    digest = F.sha2(F.concat(F.lit("sample"), F.col("id").cast("string")), 256)
    mixed = F.regexp_replace(F.base64(F.unhex(digest)), "=+$", "")
    base36 = F.concat(*[F.lower(F.conv(F.substring(digest, 1 + 12 * k, 12), 16, 36)) for k in range(5)])
    strings = spark.range(generated).select(
        F.lit(True).alias("random"),
        F.when(F.col("id") % 3 == 0, F.substring(digest, 1, 40)).when(F.col("id") % 3 == 1, mixed).otherwise(base36).alias("token"),
    )
    names = F.array(*[F.lit(x) for x in NAME_PARTS])
    pick = lambda k: F.get(names, F.pmod(F.xxhash64("id", F.lit(k)), F.lit(len(NAME_PARTS))).cast("int"))
    picked = [pick(k) for k in range(4)]
    composed = spark.range(generated).select(
        F.lit(False).alias("random"),
        F.when(F.col("id") % 4 == 0, F.concat_ws("_", *picked))
        .when(F.col("id") % 4 == 1, F.concat(picked[0], *[F.initcap(x) for x in picked[1:]]))
        .when(F.col("id") % 4 == 2, F.concat_ws("-", *picked))
        .otherwise(F.concat_ws("_", *[F.upper(x) for x in picked], (F.col("id") % 100).cast("string")))
        .alias("token"),
    )
    chosen = labels.filter("quality = 1 and doc_id is not null").select("doc_id").distinct().orderBy("doc_id").limit(max_labelled)
    prose = docs.join(F.broadcast(chosen), "doc_id", "left_semi").select(F.lit(False).alias("random"), F.explode(words(F.col("text"))).alias("token"))
    return strings.unionAll(composed).unionAll(prose)


def pair_weights(sample: DataFrame) -> DataFrame:
    """One row: log p(b | a, random) - log p(b | a, identifier) for all pairs of the alphabet, a-major."""
    n = len(ALPHABET)
    place = lambda c: F.instr(F.lit(ALPHABET), c) - 1
    chars = F.split(F.regexp_replace("token", f"[^{ALPHABET[:-1]}-]+", ""), "")
    pairs = sample.select("random", F.inline(F.arrays_zip(chars.alias("a"), F.slice(chars, F.lit(2), F.greatest(F.size(chars) - 1, F.lit(0))).alias("b"))))
    pairs = pairs.toDF("random", "a", "b").filter("length(a) = 1 and length(b) = 1")
    counted = pairs.groupBy((place(F.col("a")) * n + place(F.col("b"))).alias("pair")).agg(
        F.count_if("random").alias("r"), F.count_if(~F.col("random")).alias("o")
    )
    grid = sample.sparkSession.range(n * n).select(F.col("id").cast("int").alias("pair")).join(F.broadcast(counted), "pair", "left").fillna(0, ["r", "o"])
    by_first = grid.groupBy((F.col("pair") / n).cast("int").alias("a")).agg(F.sum("r").alias("all_r"), F.sum("o").alias("all_o"), F.array_sort(F.collect_list(F.struct("pair", "r", "o"))).alias("row"))
    log_rate = lambda x, k: F.log((x[k] + F.lit(1.0)) / (F.col(f"all_{k}") + F.lit(float(n))))
    rows = by_first.select("a", F.transform("row", lambda x: log_rate(x, "r") - log_rate(x, "o")).alias("w"))
    return rows.groupBy().agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("a", "w"))), lambda x: x["w"])).alias("weights"))


def token_score(token: Column, weights: Column) -> Column:
    """Mean log-likelihood ratio of the character pairs of ``token``."""
    codes = F.transform(F.split(token, ""), lambda c: F.instr(F.lit(ALPHABET), c) - 1)
    start = F.struct(F.lit(-1).alias("last"), F.lit(0.0).alias("sum"))
    step = lambda a, c: F.struct(c.alias("last"), F.when((a["last"] < 0) | (c < 0), a["sum"]).otherwise(a["sum"] + F.get(weights, a["last"] * len(ALPHABET) + c)).alias("sum"))
    return F.aggregate(codes, start, step, lambda a: a["sum"] / (F.length(token) - 1))


def _scanned(docs: DataFrame, carried: Column, weights: DataFrame, threshold: float) -> DataFrame:
    text = F.col("text")
    base = docs.select(carried.alias("row"), F.coalesce("text", F.lit("")).alias("text"))
    base = base.select(
        "row",
        "text",
        F.filter(_located(text, ASSIGN, 2), lambda x: F.length(x["v"]) >= 6).alias("assign"),
        _located(text, ACCESS).alias("access"),
        _located(text, HEX).alias("hex"),
        _located(text, TOKEN).alias("tokens"),
    ).withColumn("weights", weights.scalar())
    base = base.withColumn("markov", F.filter("tokens", lambda x: token_score(x["v"], F.col("weights")) > threshold))

    def of_kind(kind: str) -> Column:
        return F.transform(kind, lambda x: F.struct(x["s"].alias("s"), F.lit(KINDS.index(kind)).alias("o"), x["e"].alias("e")))

    spans = lambda *kinds: F.sort_array(F.concat(*map(of_kind, kinds)))
    return base.select("row", "text", *[F.size(k).cast("long").alias(f"n_{k}") for k in KINDS], spans(*KINDS[:3]).alias("base"), spans(*KINDS).alias("spans"))


def _said(spans: str) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["o"]), x["s"], x["e"])), ",")


def models(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The trained weights, as ``pair_weights`` returns them."""
    return pair_weights(labelled_sample(docs.sparkSession, docs.select("doc_id", "text"), labels))


def scan(docs: DataFrame, weights: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): counts by kind, base_sha256 of the fixed patterns' spans, all spans."""
    out = _scanned(docs, F.struct("doc_id"), weights, threshold)
    return out.select("row.doc_id", "n_assign", "n_access", "n_hex", F.sha2(_said("base"), 256).alias("base_sha256"), _said("spans").alias("spans"), "n_markov")


def redact(docs: DataFrame, weights: DataFrame, threshold: float = THRESHOLD, mask: str = MASK) -> DataFrame:
    """``docs`` with every reported span replaced by ``mask`` and n_chars counted anew; no row is dropped."""
    out = _scanned(docs, F.struct(*[F.col(f"`{c}`") for c in docs.columns]), weights, threshold)
    start = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<string>)").alias("out"))
    piece = lambda a, x: F.substring(F.col("text"), a["at"] + 1, F.greatest(x["s"] - a["at"], F.lit(0)))
    step = lambda a, x: F.struct(
        F.greatest(a["at"], x["e"]).alias("at"),
        F.when(x["s"] < a["at"], a["out"]).otherwise(F.concat(a["out"], F.array(piece(a, x), F.lit(mask)))).alias("out"),
    )
    clean = F.aggregate("spans", start, step, lambda a: F.array_join(F.concat(a["out"], F.array(F.substring(F.col("text"), a["at"] + 1, F.length("text")))), ""))
    out = out.withColumn("clean", F.when(F.size("spans") > 0, clean).otherwise(F.col("row.text")))
    fresh = {"text": F.col("clean"), "n_chars": F.length("clean").cast("long")}
    return out.select(*[(F.when(F.size("spans") > 0, fresh[c]).otherwise(F.col(f"row.`{c}`")) if c in fresh else F.col(f"row.`{c}`")).alias(c) for c in docs.columns])
