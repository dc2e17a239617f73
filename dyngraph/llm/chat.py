"""Chat formatting after cumulative-snapshot collapse (native).

Logs often hold the same conversation many times, each snapshot a few turns longer. A conversation's turns, in order
of turn number, get rolling prefix hashes: the sum, over the turns so far, of a hash of position, role and text, in
four lanes of 32 bits. A conversation goes when its whole hash is the hash of a proper prefix of a longer one (an
anti-join), or of an equal one with a smaller conv_id. The maximal ones are rendered turn by turn.

Running counts and sums are taken in two levels, within blocks of ``block`` turn numbers and then over the blocks'
sums, so one very long conversation is spread over many tasks. Nothing is collected to arrays. The turns with their
prefix hashes and lengths are written once, and all comparisons read the narrow columns of that table.

Results for odd input: null role or text counts and renders as empty text but differs from it in the hash; rows
without conv_id are one conversation; null turns come first; rows of a conversation that repeat turn, role and text are one
turn; equal turn numbers are ordered by role and text; an empty table gives no rows; further columns are dropped.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written

BLOCK = 512
# The markers of the rendered form.
OPEN, BREAK, CLOSE = "<|im_start|>", "\n", "<|im_end|>\n"
_LANES = 4


def _running(rows: DataFrame, sums: dict[str, Column]) -> DataFrame:
    """Adds inclusive running sums over the order of a conversation, in two levels."""
    # groups equal to NULL must meet: c and b are never null
    inner = Window.partitionBy("c", "b").orderBy("turn", "role", "text").rowsBetween(Window.unboundedPreceding, 0)
    outer = Window.partitionBy("c").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    blocks = rows.groupBy("c", "b").agg(*[F.sum(x).alias(f"_{k}") for k, x in sums.items()])
    before = blocks.select("c", "b", *[F.coalesce(F.sum(f"_{k}").over(outer), F.lit(0).cast("long")).alias(f"_{k}") for k in sums])
    within = rows.select("*", *[F.sum(x).over(inner).alias(k) for k, x in sums.items()])
    out = within.join(before, ["c", "b"])
    return out.select(*rows.columns, *[(F.col(k) + F.col(f"_{k}")).alias(k) for k in sums])


def _rendered() -> Column:
    said = lambda c: F.coalesce(F.col(c), F.lit(""))
    return F.concat(F.lit(OPEN), said("role"), F.lit(BREAK), said("text"), F.lit(CLOSE))


def turns(conversations: DataFrame, block: int = BLOCK) -> DataFrame:
    """Distinct turns with place (from 1), the prefix hash up to them (h0..h3) and upto, the rendered characters up to them."""
    rows = conversations.select("conv_id", "turn", "role", "text").distinct()
    key = F.coalesce(F.col("conv_id").cast("string"), F.lit("null"))
    rows = rows.withColumn("c", key).withColumn("b", F.coalesce(F.floor(F.col("turn") / block).cast("long"), F.lit(-(2**62))))
    placed = _running(rows, {"place": F.lit(1).cast("long")})
    lane = lambda i: F.xxhash64("place", F.col("role").isNull(), "role", F.col("text").isNull(), "text", F.lit(i // 2))
    half = lambda i: (F.shiftrightunsigned(lane(i), 32) if i % 2 else lane(i)).bitwiseAND(F.lit(2**32 - 1))
    return _running(placed, {f"h{i}": half(i) for i in range(_LANES)} | {"upto": F.length(_rendered()).cast("long")})


def maximal(conversations: DataFrame, block: int = BLOCK) -> DataFrame:
    """The distinct turns, with place, prefix hashes, upto and n (turns of the whole), of those conversations that no
    other one continues or repeats."""
    rows = written(turns(conversations, block), "turns")
    hashes = [f"h{i}" for i in range(_LANES)]
    ends = rows.groupBy("c").agg(F.max_by(F.struct("conv_id", "place", *hashes), "place").alias("e")).select("c", "e.*")
    proper = rows.select("c", "place", *hashes).join(ends.select("c", F.col("place").alias("n")), "c").filter("place < n").select("place", *hashes)
    first = ends.groupBy("place", *hashes).agg(F.min_by("c", F.struct(F.col("conv_id").isNull(), "conv_id")).alias("c"))
    kept = written(first.join(proper, ["place", *hashes], "left_anti").select("c", F.col("place").alias("n")), "kept")
    return rows.join(kept, "c")


def render(conversations: DataFrame, block: int = BLOCK) -> DataFrame:
    """One row per turn of the maximal conversations: conv_id, place, n_turns, starts (characters before it), rendered."""
    rows = maximal(conversations, block).withColumn("rendered", _rendered())
    return rows.select("conv_id", "place", F.col("n").alias("n_turns"), (F.col("upto") - F.length("rendered")).alias("starts"), "rendered")


# DuckDB: whole conversations as lists, compared with the heads of all longer ones.
ORACLE = """
WITH t AS (SELECT DISTINCT conv_id, turn, role, text FROM conversations),
p AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS place FROM t),
c AS (SELECT conv_id, list(struct_pack(r := role, x := text) ORDER BY place) AS l, count(*) AS n FROM p GROUP BY conv_id),
heads AS (SELECT DISTINCT c.l[1:p.place] AS h FROM c JOIN p USING (conv_id) WHERE p.place < c.n),
kept AS (SELECT min(conv_id) AS conv_id, any_value(n) AS n_turns FROM c WHERE l NOT IN (SELECT h FROM heads) GROUP BY l),
r AS (SELECT p.conv_id, p.place, k.n_turns, '<|im_start|>' || coalesce(role, '') || chr(10) || coalesce(text, '') || '<|im_end|>' || chr(10) AS rendered
      FROM p JOIN kept k ON p.conv_id = k.conv_id)
SELECT conv_id, place, n_turns,
       CAST(coalesce(sum(length(rendered)) OVER (PARTITION BY conv_id ORDER BY place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS starts,
       rendered
FROM r
"""
