"""Mixing sources to target weights by soft membership (native).

A multinomial naive Bayes over hashed words is trained on labelled documents and gives every document a posterior
over the domains (quality x toxic labels). With n(d) tokens and posterior p(d, k), a nonnegative rate r(d) for every
document is fitted so that the expected domain totals sum_d r(d) n(d) p(d, k) meet the targets in least squares, with
the rates as near to one as that allows. Gradients with respect to the rates are p(d) . v, for v the residual of the
totals scaled by the inverse moments of p; they are added up and the sum is projected (lazy projection), so the rate is
r(d) = max(0, 1 - p(d) . w) for one vector w of K numbers. A rate needs no storage, each step is one aggregation of a few
sums over a narrow projection, and its plan is the same at every step: w comes as the value of a one-row subquery.

Results for odd input: null or empty text has no tokens, the prior as posterior, and a rate like any other; labels
that are null count as 0; without labelled documents all mass lies in the first domain; repeated rows are fitted
each; an empty table gives no rows; further columns, whatever their names, are left alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import words, written

#: Domains in the order of the posteriors: quality * 2 + toxic.
DOMAINS = ("poor", "poor_toxic", "good", "good_toxic")
#: Wanted share of each domain's own tokens that should remain in expectation.
TARGET = (0.5, 0.0, 1.0, 0.0)
BUCKETS = 1 << 13
MAX_LABELLED = 20_000
SMOOTHING = 1.0
#: Passes over the narrow table at most.
STEPS = 40
#: Miss of each domain, as a share of its own tokens before mixing, at which fitting stops.
TOLERANCE = 1e-3
#: Weight of the rates' squared distance from one beside the squared miss of a domain, as a share of the domain's tokens:
#: what keeps a domain that only tinges other documents from being pursued at their cost.
RIDGE = 1e-4


def _bin(word: Column, buckets: int) -> Column:
    return F.xxhash64(word).bitwiseAND(F.lit(buckets - 1).cast("long")).cast("int")


def classifier(docs: DataFrame, labels: DataFrame, buckets: int = BUCKETS, max_labelled: int = MAX_LABELLED) -> DataFrame:
    """One row: prior (K log priors) and weights (for each bin an array of K log-likelihoods).

    Fitted on at most ``max_labelled`` labelled documents, chosen by a hash of their ids; counts are kept apart for
    each document once, so that a word counts as present rather than by its repeats.
    """
    k = len(DOMAINS)
    rows = labels.filter("doc_id is not null").groupBy("doc_id").agg((F.max(F.coalesce("quality", F.lit(0))) * 2 + F.max(F.coalesce("toxic", F.lit(0)))).alias("y"))
    rows = rows.filter(F.col("y").between(0, k - 1)).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_labelled)
    seen = docs.select("doc_id", "text").join(F.broadcast(rows), "doc_id").select("y", F.array_distinct(words(F.col("text"))).alias("w"))
    grid = lambda *extra: [F.count_if(F.col("y") == i).alias(f"c{i}") for i in range(k)]
    counts = seen.select("y", F.explode("w").alias("w")).groupBy(_bin(F.col("w"), buckets).alias("bin")).agg(*grid())
    zeros = docs.sparkSession.range(buckets).select(F.col("id").cast("int").alias("bin")).join(F.broadcast(counts), "bin", "left").fillna(0)
    gathered = zeros.groupBy().agg(F.array_sort(F.collect_list(F.struct("bin", F.array(*[f"c{i}" for i in range(k)]).alias("c")))).alias("rows"), *[F.sum(f"c{i}").alias(f"t{i}") for i in range(k)])
    rate = lambda x, i: F.log((F.get(x["c"], F.lit(i)) + F.lit(SMOOTHING)) / (F.col(f"t{i}") + F.lit(SMOOTHING * buckets)))
    weights = gathered.select(F.transform("rows", lambda x: F.array(*[rate(x, i) for i in range(k)])).alias("weights"))
    size = seen.groupBy().agg(*grid(), F.count(F.lit(1)).alias("n"))
    prior = size.select(F.array(*[F.log((F.col(f"c{i}") + F.lit(1.0 if i == 0 else 0.01)) / (F.col("n") + F.lit(1.0 + 0.01 * (k - 1)))) for i in range(k)]).alias("prior"))
    return prior.join(F.broadcast(weights))


def posteriors(docs: DataFrame, carried: Column, model: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """``carried`` as row, n_tokens and p (K posteriors). One scan, no shuffle; the model comes as scalar subqueries."""
    k = len(DOMAINS)
    w = docs.select(carried.alias("row"), words(F.col("text")).alias("w"))
    w = w.select("row", F.size("w").cast("long").alias("n_tokens"), F.array_distinct("w").alias("w"))
    w = w.withColumn("weights", model.select("weights").scalar()).withColumn("prior", model.select("prior").scalar())
    sums = F.aggregate(
        F.transform("w", lambda x: F.get("weights", _bin(x, buckets))),
        F.struct(*[F.get("prior", F.lit(i)).alias(f"s{i}") for i in range(k)]),
        lambda a, x: F.struct(*[(a[f"s{i}"] + F.get(x, F.lit(i))).alias(f"s{i}") for i in range(k)]),
    )
    w = w.select("row", "n_tokens", sums.alias("s"))
    top = F.greatest(*[F.col(f"s.s{i}") for i in range(k)])
    w = w.select("row", "n_tokens", F.array(*[F.exp(F.col(f"s.s{i}") - top) for i in range(k)]).alias("e"))
    total = F.aggregate("e", F.lit(0.0), lambda a, x: a + x)
    return w.select("row", "n_tokens", F.transform("e", lambda x: x / total).alias("p"))


def _rate(w: Column, k: int) -> Column:
    """max(0, 1 - p . w) for an array column ``w`` beside the posteriors ``p``."""
    dot = F.get("p", F.lit(0)) * F.get(w, F.lit(0))
    for i in range(1, k):
        dot = dot + F.get("p", F.lit(i)) * F.get(w, F.lit(i))
    return F.greatest(F.lit(0.0), F.lit(1.0) - dot)


def rated(df: DataFrame, w: list[float]) -> DataFrame:
    """``df`` (with posteriors ``p``) and its column ``rate``; the plan does not depend on the numbers in ``w``."""
    held = df.sparkSession.range(1).select(F.array(*[F.lit(float(x)) for x in w]).alias("w"))
    return df.withColumn("_w", held.scalar()).withColumn("rate", _rate(F.col("_w"), len(w))).drop("_w")


def _solved(matrix: list[list[float]], right: list[float]) -> list[float]:
    """Solution of a few equations by elimination with pivots."""
    n = len(right)
    rows = [[*matrix[i], right[i]] for i in range(n)]
    for c in range(n):
        best = max(range(c, n), key=lambda r: abs(rows[r][c]))
        rows[c], rows[best] = rows[best], rows[c]
        for r in range(n):
            if r != c and rows[c][c]:
                f = rows[r][c] / rows[c][c]
                rows[r] = [x - f * y for x, y in zip(rows[r], rows[c], strict=True)]
    return [rows[i][n] / rows[i][i] if rows[i][i] else 0.0 for i in range(n)]


def fit(narrow: DataFrame, target: tuple[float, ...] = TARGET, steps: int = STEPS, tolerance: float = TOLERANCE) -> tuple[list[float], list[dict]]:
    """The vector w of the rates over (n_tokens, p), and the totals after each accepted step.

    A pass gives, by tokens, the K totals and the K x K moments of p over documents of positive rate, and the sum of the
    squared rates; only those reach the driver. The objective is sum n (r - 1)^2 / 2 + sum_k miss_k^2 / (2 c_k) with c_k
    ``RIDGE`` times the domain's tokens, whose dual is smooth and convex in w; a step solves the moments' equations for the
    residual and is halved while the dual does not fall. Fitting ends when every domain is within ``tolerance`` of its
    target by its own size, when the residual of the penalised problem is gone, or after ``steps`` passes.
    """
    k = len(target)
    p = [F.get("p", F.lit(i)) for i in range(k)]
    pairs = [(i, j) for i in range(k) for j in range(i, k)]

    def passed(w: list[float]) -> tuple[list[float], list[list[float]], float, float]:
        df = rated(narrow.select("n_tokens", "p"), w)
        r, live = F.col("rate"), F.when(F.col("rate") > 0, F.col("n_tokens")).otherwise(0)
        row = df.agg(F.sum("n_tokens").alias("n"), F.sum(F.col("n_tokens") * r * r).alias("rr"), *[F.sum(F.col("n_tokens") * r * p[i]).alias(f"t{i}") for i in range(k)], *[F.sum(live * p[i] * p[j]).alias(f"m{i}_{j}") for i, j in pairs]).first()
        moments = [[(row[f"m{min(i, j)}_{max(i, j)}"] or 0.0) for j in range(k)] for i in range(k)]
        return [row[f"t{i}"] or 0.0 for i in range(k)], moments, row["rr"] or 0.0, float(row["n"] or 0)

    w = [0.0] * k
    now, moments, squares, tokens = passed(w)
    if not tokens:
        return w, []
    wanted = [target[i] * now[i] for i in range(k)]
    own = [max(x, 1e-9 * tokens) for x in now]
    ridge = [RIDGE * x for x in own]
    dual = lambda w, squares: 0.5 * squares + sum(a * b + 0.5 * c * a * a for a, b, c in zip(w, wanted, ridge, strict=True))
    miss = lambda now: [(a - b) / c for a, b, c in zip(now, wanted, own, strict=True)]
    log, value, used = [{"w": w, "totals": now, "miss": miss(now)}], dual(w, squares), 1
    while used < steps and max(map(abs, miss(now))) > tolerance:
        left = [a - b - c * x for a, b, c, x in zip(now, wanted, ridge, w, strict=True)]
        if max(abs(a) / b for a, b in zip(left, own, strict=True)) <= 0.1 * tolerance:
            break
        step = _solved([[moments[i][j] + (ridge[i] if i == j else 0.0) for j in range(k)] for i in range(k)], left)
        size, better = 1.0, False
        while used < steps and not better and size > 1e-4:
            trial = [a + size * b for a, b in zip(w, step, strict=True)]
            then, fresh, squares, _ = passed(trial)
            used += 1
            better = dual(trial, squares) < value
            size /= 2
        if not better:
            break
        w, now, moments, value = trial, then, fresh, dual(trial, squares)
        log.append({"w": w, "totals": now, "miss": miss(now)})
    return w, log


def copies(rate: Column, key: Column) -> Column:
    """Whole number of copies: the rate's fraction is rounded up or down by a hash of ``key``, exact in expectation."""
    coin = F.pmod(F.xxhash64(key, F.lit("mixing")), F.lit(1_000_003).cast("long")) / F.lit(1_000_003.0)
    return (F.floor(rate) + (coin < rate - F.floor(rate)).cast("long")).cast("int")


def _fitted(docs: DataFrame, carried: Column, labels: DataFrame, target: tuple[float, ...], steps: int) -> DataFrame:
    """``carried`` as row, n_tokens, p and rate. Posteriors are computed once, beside the row, and written; the fit reads
    the two narrow columns of that table only."""
    model = written(classifier(docs, labels), "classifier")
    wide = written(posteriors(docs, carried, model), "posteriors")
    w, _ = fit(wide, target, steps)
    return rated(wide, w)


def rates(docs: DataFrame, labels: DataFrame, target: tuple[float, ...] = TARGET, steps: int = STEPS) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_tokens, one posterior column a domain, rate and copies."""
    out = _fitted(docs, F.struct("doc_id"), labels, target, steps)
    return out.select("row.doc_id", "n_tokens", *[F.round(F.get("p", F.lit(i)), 6).alias(f"p_{d}") for i, d in enumerate(DOMAINS)], F.round("rate", 6).alias("rate"), copies(F.col("rate"), F.col("row.doc_id")).alias("copies"))


def mix(docs: DataFrame, labels: DataFrame, target: tuple[float, ...] = TARGET, steps: int = STEPS) -> DataFrame:
    """``docs`` with each row repeated as often as its rate says, which may be never."""
    whole = _fitted(docs, F.struct(*[F.col(f"`{c}`") for c in docs.columns]), labels, target, steps)
    whole = whole.select("row", copies(F.col("rate"), F.col("row.doc_id")).alias("copies"))
    return whole.select(F.explode(F.array_repeat("row", F.col("copies"))).alias("row")).select("row.*")
