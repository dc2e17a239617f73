"""MinHash near-duplicates with tensored banding, verified on full shingle sets.

A document's set holds its distinct k-word shingles as 64-bit hashes. Documents with equal sets form one class, and
only one row of each class goes on. Two small collections of ``side`` groups of ``rows`` minhashes are computed;
table (i, j) is keyed by group i of the first collection combined with group j of the second, so side**2 tables of
2*rows hashes each cost only 2*side*rows minhashes. Classes that meet in a table are candidates, and a link is made
only where the full sets have Jaccard similarity ``percent``/100 or more.

Two classes meet in table (i, j) only where they share both groups, so groups that one class alone has are dropped
first and tables are keyed by pairs of what is left: the same candidates from a fraction of the rows.

Candidates are not expanded to all pairs of a table entry, and no member carries its entries through a join. First
the side tables (i, i) alone link members to their entry's centre, the member whose groups are fullest, and links join
components. Then all tables are summed up by component: an entry that one component fills needs no more. Of the others,
those of up to ``few`` classes have all their pairs compared; in larger ones the members outside the largest component
are compared with its centre, if they share ``SHARED`` tables with it. Where an entry then still holds several
components, the members outside its largest one are compared exactly, in blocks within one task each, with everything
that shares a group of the first collection; a task returns one link for two components at most. So a link that joins
two components is missed only where both ends share no table: at similarity 0.8 with the default sizes about 7 in
100,000 pairs, at 0.9 none in 10**9.

Results for odd input: null or empty text has an empty set and is linked with nothing; a row without doc_id is its
own document (component_id null, kept true); rows that repeat a doc_id are one document; with fewer words than a
shingle the whole sequence is the one shingle; an empty table gives no rows; further columns are left alone.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

SHINGLE = 5
PERCENT = 80
SIDE = 10
ROWS = 2
FEW = 4
#: Members outside their entry's largest component, and others, that one task compares at a time.
BLOCK_LEFT, BLOCK_ALL = 256, 2048
#: Tables, of the ``side`` first and of all, that a member must share with a centre to be compared with it at once; others
#: wait for the exact comparison.
SHARED_FIRST, SHARED = 2, 6
#: Ids that may be broadcast when full sets are computed anew (about 60 MB); with more, the texts are shuffled.
BROADCAST_IDS = 1_000_000
_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
_BLOCK = 4096


def _odd(n: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _mixed(h: np.ndarray) -> np.ndarray:
    h ^= h >> np.uint64(31)
    h *= np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    return h


def shingle_set(text: bytes, k: int) -> np.ndarray:
    """Sorted distinct hashes of the k-word shingles of UTF-8 ``text``."""
    words = text.translate(_LOWER).split()  # bytes.split() takes exactly the six white-space bytes
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, n)
    wide = min(k, n)
    factors = _odd(k, 20 + wide)
    out = h[: n - wide + 1] * factors[0]
    for i in range(1, wide):
        out += h[i : n - wide + 1 + i] * factors[i]
    return np.unique(_mixed(out))


def minhashes(shingles: np.ndarray, factors: np.ndarray) -> np.ndarray:
    """Smallest value of every hash function over the set, in blocks so that memory stays bounded."""
    least = np.full(len(factors), np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(shingles), _BLOCK):
        np.minimum(least, (shingles[i : i + _BLOCK, None] * factors).min(axis=0), out=least)
    return least


def _bytes(column: pa.Array) -> Iterator[bytes]:
    for x in column.cast(pa.binary() if column.type == pa.string() else pa.large_binary()):
        yield x.as_py() or b""


def signatures(docs: DataFrame, shingle: int = SHINGLE, side: int = SIDE, rows: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, set_key (128-bit hash of the set), one and two (the two collections of group keys)."""
    factors = _odd(2 * side * rows, 7)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, keys, groups = [], [], ([], [])
            for text in _bytes(batch.column("text")):
                found = shingle_set(text, shingle)
                sizes.append(len(found))
                if not len(found):
                    keys.append(None)
                    groups[0].append(None)
                    groups[1].append(None)
                    continue
                keys.append(xxhash.xxh3_128_digest(found.tobytes()))
                least = minhashes(found, factors).reshape(2, side, rows)
                folded = least[:, :, 0].copy()
                for r in range(1, rows):
                    folded = _mixed(folded) + least[:, :, r]
                for g, x in zip(groups, _mixed(folded).view(np.int64), strict=True):
                    g.append(x)
            long_list = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(keys, pa.binary()), *[pa.array(g, long_list) for g in groups]],
                names=["doc_id", "n_shingles", "set_key", "one", "two"],
            )

    return docs.select("doc_id", "text").mapInArrow(work, "doc_id long, n_shingles long, set_key binary, one array<long>, two array<long>")


def full_sets(docs: DataFrame, shingle: int) -> DataFrame:
    """doc_id and its whole set as an array."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [shingle_set(t, shingle).view(np.int64) for t in _bytes(batch.column("text"))]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(found, pa.list_(pa.int64()))], names=["doc_id", "shingles"])

    return docs.select("doc_id", "text").mapInArrow(work, "doc_id long, shingles array<long>")


def components(edges: DataFrame, max_rounds: int = 64) -> DataFrame:
    """node and component (its smallest reachable node) for all nodes of ``edges`` (a, b).

    Every round points each node at its smallest neighbour, shortens the pointers, and goes on with the contracted
    edges, whose nodes at least halve. Only counts reach the driver.
    """
    edges = written(edges.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    nodes = edges.select(F.col("a").alias("node")).union(edges.select(F.col("b").alias("node"))).distinct()
    found = written(nodes.select("node", F.col("node").alias("component")), "nodes")
    for rounds in range(max_rounds + 1):
        if edges.isEmpty():
            break
        if rounds == max_rounds:
            raise RuntimeError(f"components did not settle in {max_rounds} rounds")
        both = edges.union(edges.select("b", "a"))
        to = both.groupBy(F.col("a").alias("v")).agg(F.least(F.min("b"), F.first("a")).alias("p"))
        jump = lambda x: x.join(to.select(F.col("v").alias("p"), F.col("p").alias("q")), "p", "left").select("v", F.coalesce("q", "p").alias("p"))
        to = written(jump(jump(to)), "pointers")
        found = written(
            found.join(to.select(F.col("v").alias("component"), "p"), "component", "left").select("node", F.coalesce("p", "component").alias("component")), "components"
        )
        edges = written(
            edges.join(to.select(F.col("v").alias("a"), F.col("p").alias("pa")), "a").join(to.select(F.col("v").alias("b"), F.col("p").alias("pb")), "b")
            .filter("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(),
            "edges",
        )
    return found


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between components (a, b), from those pairs (a, b, comp_a, comp_b) whose full sets are similar enough."""
    both = pairs.join(sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("x")), "a").join(sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("y")), "b")
    common = both.select("comp_a", "comp_b", F.size("x").alias("m"), F.size("y").alias("n"), F.size(F.array_intersect("x", "y")).alias("c"))
    similar = common.filter(F.lit(100).cast("long") * F.col("c") >= percent * (F.col("m") + F.col("n") - F.col("c")))
    return similar.select(F.col("comp_a").alias("a"), F.col("comp_b").alias("b")).distinct()


def _fits(percent: int, m: str = "m", n: str = "n") -> str:
    return f"100 * least({m}, {n}) >= {percent} * greatest({m}, {n})"


def _sets_of(docs: DataFrame, ids: DataFrame, shingle: int) -> DataFrame:
    """The full sets of some documents, computed anew from their text, written once."""
    ids = written(ids.distinct(), "ids")
    few = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    some = docs.filter("doc_id is not null").select("doc_id", "text").join(F.broadcast(ids) if few else ids, "doc_id", "left_semi")
    return written(full_sets(some, shingle), "sets")


def _members(reps: DataFrame) -> DataFrame:
    """rep, n, its groups of both collections that several classes have, and weight: how full those groups are."""
    named = lambda c, s: F.transform(c, lambda x, i: F.struct(F.lit(s).alias("side"), i.alias("i"), x.alias("x")))
    groups = reps.select("rep", "n", F.inline(F.concat(named("one", 0), named("two", 1))))
    shared = groups.groupBy("side", "i", "x").agg(F.count(F.lit(1)).alias("size")).filter("size > 1")
    met = groups.join(shared, ["side", "i", "x"])
    of = lambda s: F.collect_list(F.when(F.col("side") == s, F.struct("i", "x")))  # noqa: E731  at most ``side`` entries
    return met.groupBy("rep").agg(F.first("n").alias("n"), of(0).alias("one"), of(1).alias("two"), F.sum("size").alias("weight"))


def _entries(members: DataFrame, labels: DataFrame, first: bool = False) -> DataFrame:
    """key, rep, n, weight and comp of every table entry; with ``first`` those of the tables (i, i) only."""
    other = lambda a: F.filter("two", lambda b: b["i"] == a["i"]) if first else F.col("two")
    keys = F.flatten(F.transform("one", lambda a: F.transform(other(a), lambda b: F.xxhash64(a["x"], b["x"], a["i"], b["i"]))))
    return members.join(labels, "rep").select(F.explode(keys).alias("key"), "rep", "n", "weight", "comp")


def _open_tables(entries: DataFrame) -> DataFrame:
    """Keys that several components share: size (members), most (the largest component), its centre and the centre's n."""
    each = entries.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("size"), F.max(F.struct("weight", (-F.col("rep")).alias("back"), "n")).alias("c"))
    found = each.groupBy("key").agg(F.count(F.lit(1)).alias("parts"), F.sum("size").alias("size"), F.max(F.struct("size", "c.weight", (-F.col("comp")).alias("back"), "c")).alias("m"))
    return found.filter("parts > 1").select("key", "size", (-F.col("m.back")).alias("most"), (-F.col("m.c.back")).alias("centre"), F.col("m.c.n").alias("centre_n"))


def _outside(entries: DataFrame, tables: DataFrame) -> DataFrame:
    """Entries outside their table's largest component, beside the table."""
    tables = tables.withColumnRenamed("key", "k")
    return entries.join(tables, (F.col("key") == F.col("k")) & (F.col("comp") != F.col("most"))).drop("k")


def _star(outside: DataFrame, shared: int, percent: int) -> DataFrame:
    """Pairs of a centre and a member outside its component that share ``shared`` tables and could be similar by size."""
    some = outside.filter(_fits(percent, "n", "centre_n")).groupBy("centre", "rep", "most", "comp").agg(F.count(F.lit(1)).alias("tables"))
    return some.filter(F.col("tables") >= shared).select(F.col("centre").alias("a"), F.col("rep").alias("b"), F.col("most").alias("comp_a"), F.col("comp").alias("comp_b"))


def _all_pairs(small: DataFrame, percent: int) -> DataFrame:
    """All pairs of different components within tables of a few members."""
    side = lambda x: small.select("key", F.col("rep").alias(x), F.col("n").alias(f"n_{x}"), F.col("comp").alias(f"comp_{x}"))
    both = side("a").join(side("b"), "key").filter((F.col("a") < F.col("b")) & (F.col("comp_a") != F.col("comp_b")))
    return both.filter(_fits(percent, "n_a", "n_b")).select("a", "b", "comp_a", "comp_b")


def _joined(labels: DataFrame, links: DataFrame) -> DataFrame:
    """``labels`` (rep, comp) after the links between components."""
    into = components(links).select(F.col("node").alias("comp"), F.col("component").alias("into"))
    return written(labels.join(into, "comp", "left").select("rep", F.coalesce("into", "comp").alias("comp")), "labels")


def _compared(docs: DataFrame, pairs: DataFrame, labels: DataFrame, shingle: int, percent: int) -> DataFrame:
    pairs = written(pairs.distinct(), "pairs")
    sets = _sets_of(docs, pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")), shingle)
    return _joined(labels, _verified(pairs, sets, percent))


def block_links(left: pa.Table, every: pa.Table, percent: int) -> pa.Table:
    """Links (a, b) between the components of rows of ``left`` and of ``every`` (g, rep, comp, shingles) of one g.

    The shingles of ``left``, keyed with g, are one sorted list of postings that each other row looks its own up in.
    """
    out: set[tuple[int, int]] = set()
    if left.num_rows and every.num_rows:
        sides = []
        for t in (left, every):
            t = t.combine_chunks()
            lists = t.column("shingles").chunk(0)
            bounds = lists.offsets.to_numpy()
            salt = _mixed(t.column("g").to_numpy().view(np.uint64).copy())
            flat = lists.values.to_numpy()[bounds[0] : bounds[-1]].view(np.uint64) ^ np.repeat(salt, np.diff(bounds))
            sides.append((flat, bounds - bounds[0], t.column("comp").to_numpy()))
        (flat, bounds, comps), (keys, ends, theirs) = sides
        sizes = np.diff(bounds)
        order = np.argsort(flat, kind="stable")
        flat, owner = flat[order], np.repeat(np.arange(len(sizes)), sizes)[order]
        for j in range(len(theirs)):
            k = keys[ends[j] : ends[j + 1]]
            lo = np.searchsorted(flat, k, "left")
            n = np.searchsorted(flat, k, "right") - lo
            hits = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(int(n.sum()))
            common = np.bincount(owner[hits], minlength=len(sizes))
            for i in np.flatnonzero((100 * common >= percent * (sizes + len(k) - common)) & (comps != theirs[j])):
                out.add((min(int(comps[i]), int(theirs[j])), max(int(comps[i]), int(theirs[j]))))
    return pa.table({"a": pa.array([x[0] for x in out], pa.int64()), "b": pa.array([x[1] for x in out], pa.int64())})


def _left_over(docs: DataFrame, members: DataFrame, labels: DataFrame, shingle: int, percent: int, few: int) -> DataFrame | None:
    """Links of members that the first comparisons left outside their entry's largest component; exact, in blocks."""
    entries = _entries(members, labels)
    left = written(_outside(entries, _open_tables(entries).filter(F.col("size") > few)).select("rep").distinct(), "left")
    if left.isEmpty():
        return None
    groups = members.select("rep", F.explode(F.transform("one", lambda x: F.xxhash64(x["x"], x["i"]))).alias("g"))
    groups = groups.join(labels, "rep").select("g", "rep", "comp")
    some = groups.join(left, "rep", "left_semi")
    sizes = groups.join(some.groupBy("g").agg(F.count(F.lit(1)).alias("n_left")), "g").groupBy("g").agg(
        F.first("n_left").alias("n_left"), F.count(F.lit(1)).alias("n_all"), F.min("comp").alias("lo"), F.max("comp").alias("hi")
    )
    sizes = written(sizes.filter("lo <> hi").select("g", "n_all", F.ceil(F.col("n_left") / BLOCK_LEFT).cast("int").alias("bl"), F.ceil(F.col("n_all") / BLOCK_ALL).cast("int").alias("ba")), "groups")
    block = lambda n, seed: F.pmod(F.xxhash64("rep", F.lit(seed)), F.col(n)).cast("int")
    other = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    ours = written(some.join(sizes, "g").select("g", "rep", "comp", block("bl", 1).alias("i"), other("ba").alias("j")), "ours")
    theirs = written(groups.join(sizes, "g").select("g", "rep", "comp", block("ba", 2).alias("j"), other("bl").alias("i")), "theirs")
    sets = _sets_of(docs, theirs.select(F.col("rep").alias("doc_id")), shingle).select(F.col("doc_id").alias("rep"), "shingles")
    tasks = (sizes.agg(F.sum("n_all")).first()[0] or 0) // BLOCK_ALL + 1
    task = F.pmod(F.xxhash64("g"), F.lit(tasks)).alias("task")  # small groups share a task, as many as fill a block
    shape = [task, "i", "j", "g", "rep", "comp", "shingles"]

    def compare(a: pa.Table, b: pa.Table) -> pa.Table:
        return block_links(a, b, percent)

    names = ["task", "i", "j", "g", "rep", "comp", "shingles"]
    one, two = (x.join(sets, "rep").select(*shape).toDF(*names) for x in (ours, theirs))
    return one.groupBy("task", "i", "j").cogroup(two.groupBy("task", "i", "j")).applyInArrow(compare, "a long, b long")


def classes(docs: DataFrame, shingle: int = SHINGLE, percent: int = PERCENT, side: int = SIDE, rows: int = ROWS, few: int = FEW) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_shingles, component_id (smallest doc_id reachable) and kept."""
    signed = written(signatures(docs, shingle, side, rows), "signatures")
    some = signed.filter("n_shingles > 0 and doc_id is not null")
    reps = written(some.groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"), F.first("one").alias("one"), F.first("two").alias("two")), "classes")
    members = written(_members(reps), "members")
    labels = members.select("rep", F.col("rep").alias("comp"))
    entries = _entries(members, labels, first=True)
    labels = _compared(docs, _star(_outside(entries, _open_tables(entries)), SHARED_FIRST, percent), labels, shingle, percent)
    entries = _entries(members, labels)
    tables = written(_open_tables(entries), "tables")
    large, small = tables.filter(F.col("size") > few), tables.filter(F.col("size") <= few).select("key")
    pairs = _star(_outside(entries, large), SHARED, percent).unionAll(_all_pairs(written(entries.join(small, "key"), "small"), percent))
    labels = _compared(docs, pairs, labels, shingle, percent)
    more = _left_over(docs, members, labels, shingle, percent, few)
    if more is not None:
        labels = _joined(labels, written(more, "links"))
    roots = reps.select("set_key", "rep").join(labels, "rep", "left").select("set_key", F.coalesce("comp", "rep").alias("root"))
    out = signed.join(roots, "set_key", "left")
    out = out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("root", "doc_id")).alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("component_id") == F.col("doc_id"), F.lit(True)))


def keep_one(docs: DataFrame, **settings) -> DataFrame:
    """The rows of ``docs`` that stay: one document of each component, one row of each repeated doc_id."""
    chosen = classes(docs, **settings)
    gone = chosen.filter("not kept").select("doc_id").distinct()
    repeated = chosen.groupBy("doc_id").agg(F.count(F.lit(1)).alias("size")).filter("size > 1 and doc_id is not null").select("doc_id")
    kept = docs.join(gone, "doc_id", "left_anti")
    single = kept.join(repeated, "doc_id", "left_anti")
    again = kept.join(repeated, "doc_id", "left_semi").dropDuplicates(["doc_id"])
    return single.unionByName(again).select(*[F.col(f"`{c}`") for c in docs.columns])


# DuckDB: shingles as lists of words, all pairs that share one, and the transitive closure of the links.
ORACLE = r"""
WITH RECURSIVE t AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
sh AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(w[i:i + 3], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM t WHERE len(w) > 0)),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM sh GROUP BY 1),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM sh a JOIN sh b USING (s) WHERE a.doc_id < b.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * k >= 80 * (x.n + y.n - k)),
e AS MATERIALIZED (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r AS (SELECT DISTINCT a AS v, a AS m FROM e UNION SELECT e.b, r.m FROM r JOIN e ON e.a = r.v WHERE r.m < e.b),
g AS (SELECT v, min(m) AS m FROM r GROUP BY 1)
SELECT doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, least(doc_id, coalesce(m, doc_id)) AS component_id, doc_id <= coalesce(m, doc_id) AS kept
FROM documents LEFT JOIN n USING (doc_id) LEFT JOIN g ON g.v = doc_id
"""
