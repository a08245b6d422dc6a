"""SimHash near-duplicates by covering locality-sensitive hashing.

A 64-bit fingerprint is the bitwise majority of the XXH64 hashes of a document's word shingles. For a radius r, bit i gets
a fixed nonzero vector m(i) of r+1 bits, and each of the 2**(r+1)-1 nonzero vectors v makes a mask: the bits i with odd
<m(i), v>. Some v is orthogonal to the vectors of any r bits, so two fingerprints within the radius agree on all of some
mask: no pair is missed. Equal fingerprints are one class from the start, and the classes alone are bucketed.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqstat.llm.graph import components
from seqstat.llm.shared import ascii_words, attach_class, scratch, stage

#: Fixed value: the seed of the shingle hash.
SEED = 42
#: Buckets of more classes than this aren't paired one by one.
SMALL = 48
#: Columns of 64 bits that hold, for 256 classes of shingles, whether a set has an odd number of them.
PARITIES = ["p0", "p1", "p2", "p3"]
#: The bits of a shingle's hash by which its frequency is looked up: fewer bits cross the network, and two shingles that share them share a rank.
LEADING = (1 << 64) - (1 << 24)
#: Bytes of text whose shingles one task counts.
TASK_TEXT = 8 << 20


def shingle_hashes(words: list[bytes], n: int) -> np.ndarray:
    """XXH64 of every run of n words, repeats included; the whole sequence if there are fewer; nothing without words."""
    if not words:
        return np.empty(0, np.uint64)
    joined, digest = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= n:
        return np.array([digest(joined, SEED)], np.uint64)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = ends - lengths
    spans = zip(starts[: len(words) - n + 1].tolist(), ends[n - 1 :].tolist(), strict=True)
    return np.fromiter((digest(joined[a:b], SEED) for a, b in spans), np.uint64, len(words) - n + 1)


def majority(hashes: np.ndarray) -> int:
    """Bits set in over half the hashes; counted in blocks, so that a long text needs no more memory."""
    if not len(hashes):
        return 0
    ones = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 16):
        block = hashes[i : i + (1 << 16)].astype(">u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(block, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(hashes)).tobytes(), "big", signed=True)


def fingerprints(docs: DataFrame, words: int = 3, distinct: bool = False) -> DataFrame:
    """(doc_id, fp long) for every row; ``distinct`` counts each different shingle once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes = (shingle_hashes(ascii_words(t.as_py()), words) for t in batch.column(1))
            fps = [majority(np.unique(h) if distinct else h) for h in hashes]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps, pa.int64())], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, fp long")


def covering_masks(radius: int) -> list[int]:
    """2**(radius+1)-1 masks of 64 bits, as signed longs."""
    n = (1 << (radius + 1)) - 1
    vectors = [(i * 37) % n + 1 for i in range(64)]
    masks = [sum(1 << i for i, m in enumerate(vectors) if (m & v).bit_count() & 1) for v in range(1, n + 1)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def buckets(classes: DataFrame, radius: int, also: tuple[str, ...] = ()) -> DataFrame:
    """(bucket, mask, fp, rep): every class under every mask. The bucket is a hash of the mask, the masked bits and the columns
    ``also``: two that collide only share candidates, which are compared bit by bit anyway."""
    masks = F.array(*[F.lit(m).cast("long") for m in covering_masks(radius)])
    exploded = classes.select("*", F.explode(masks).alias("mask"))
    return exploded.withColumn("bucket", F.xxhash64("mask", F.col("fp").bitwiseAND(F.col("mask")), *also))


def crowded(entries: DataFrame) -> DataFrame:
    """(bucket, n) of the buckets that hold two classes or more."""
    return entries.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1")


def distance(x: Column, y: Column) -> Column:
    return F.bit_count(x.bitwiseXOR(y))


def small_pairs(entries: DataFrame, counts: DataFrame, radius: int) -> DataFrame:
    """All pairs within the radius (fp and rep of both) of buckets of at most SMALL classes."""
    few = entries.join(counts.where(F.col("n") <= SMALL), "bucket")
    lists = few.groupBy("bucket").agg(F.collect_list(F.struct("fp", "rep")).alias("all"))
    left = lists.select("all", F.explode("all").alias("x"))
    near = F.filter("all", lambda y: (y["rep"] > F.col("x.rep")) & (distance(y["fp"], F.col("x.fp")) <= radius))
    pairs = left.select("x", F.explode(near).alias("y"))
    return pairs.select(F.col("x.fp").alias("fp_a"), F.col("x.rep").alias("a"), F.col("y.fp").alias("fp_b"), F.col("y.rep").alias("b"))


def crowded_links(entries: DataFrame, counts: DataFrame) -> DataFrame:
    """Links (a, b) that join what is within radius 2 in buckets of more than SMALL classes.

    Two fingerprints differ in at most 2 bits exactly if some z differs from either in at most one. In a bucket z can only
    differ where the mask is clear, so each class sends itself to those z, and each z links its classes with the least:
    as many rows as clear bits for each class, whatever the bucket's size, and no link lost or added.
    """
    many = entries.join(counts.where(F.col("n") > SMALL), "bucket")
    flips = F.array(F.lit(0).cast("long"), *[F.lit(1 << i if i < 63 else -(1 << 63)).cast("long") for i in range(64)])
    clear = F.filter(flips, lambda z: z.bitwiseAND(F.col("mask")) == 0)
    balls = many.select("rep", "mask", "fp", F.explode(clear).alias("flip")).select("rep", "mask", F.col("fp").bitwiseXOR(F.col("flip")).alias("z"))
    balls = balls.select("rep", "z").distinct()
    least = balls.groupBy("z").agg(F.min("rep").alias("least"), F.max("rep").alias("most")).where("least < most")
    return balls.join(least, "z").where("rep <> least").select(F.col("least").alias("a"), F.col("rep").alias("b")).distinct()


def fingerprint_components(docs: DataFrame, words: int = 3) -> DataFrame:
    """(doc_id, fp, component_id) for every row: documents whose fingerprints differ in at most 2 bits are linked.

    Null, empty and blank texts have fingerprint zero and link like any other; ties and repeated rows share a
    fingerprint and so a component; rows without an id link too, and a component of such rows alone has no id; an empty table
    gives no rows; other columns are ignored.
    """
    rows = stage(fingerprints(docs, words), "fingerprints")
    classes = stage(rows.groupBy("fp").agg(F.min("doc_id").alias("least")), "classes")
    entries = buckets(classes.select("fp", F.col("fp").alias("rep")), 2)
    counts = stage(crowded(entries), "crowded")
    links = small_pairs(entries, counts, 2).select("a", "b").union(crowded_links(entries, counts))
    joined = stage(components(links).join(classes.withColumnRenamed("fp", "node"), "node"), "joined")
    least = joined.groupBy("component").agg(F.min("least").alias("component_id"))
    linked = joined.join(least, "component").select(F.col("node").alias("fp"), "component_id")
    alone = classes.join(linked.select("fp"), "fp", "left_anti").select("fp", F.col("least").alias("component_id"))
    return attach_class(rows, "fp", linked.union(alone), "doc_id").select("doc_id", "fp", "component_id")


def shingle_sets(docs: DataFrame, words: int) -> DataFrame:
    """(id, shingles): the distinct shingle hashes of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [np.unique(shingle_hashes(ascii_words(t.as_py()), words)).view(np.int64) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], ["id", "shingles"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "id long, shingles array<long>")


def common_shingles(docs: DataFrame, words: int, most: int = 500_000) -> tuple[np.ndarray, np.ndarray]:
    """(leading bits of hashes in order, rows that hold them): the commonest shingles, counted over all rows.

    They only set the order in which ``prefix`` takes shingles, so the bound of the table decides the cost and never the result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [np.unique(shingle_hashes(ascii_words(t.as_py()), words) & np.uint64(LEADING)) for t in batch.column(0)]
            found, n = np.unique(np.concatenate([np.empty(0, np.uint64), *sets]), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), pa.array(n, pa.int64())], ["shingle", "n"])

    with scratch(docs.sparkSession):
        # Most shingles occur once, so tables of them before the exchange would combine little and spill.
        octets = docs.agg(F.sum(F.octet_length(F.col("text").cast("string")))).first()[0] or 0
        parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-octets // TASK_TEXT))
        drawn = docs.select(F.col("text").cast("string")).mapInArrow(run, "shingle long, n long").repartition(parts, "shingle")
        counts = stage(drawn.groupBy("shingle").agg(F.sum("n").alias("n")).where("n > 1"), "common")
        least, total = 2, 0
        for r in sorted(counts.groupBy("n").agg(F.count(F.lit(1)).alias("kinds")).collect(), reverse=True):
            total += r["kinds"]
            if total > most:
                least = r["n"] + 1
                break
        found = counts.where(F.col("n") >= least).toArrow()
    hashes = found["shingle"].to_numpy().astype(np.int64).view(np.uint64)
    order = np.argsort(hashes)
    return hashes[order], found["n"].to_numpy()[order]


def prefix(hashes: np.ndarray, common: np.ndarray, counts: np.ndarray, similarity: float) -> np.ndarray:
    """The first shingles of a set in one order of all shingles (those without a count first, then the rarer), so many that two
    sets of this Jaccard similarity or more share one of them. The empty set has zero."""
    if not len(hashes):
        return np.zeros(1, np.uint64)
    rank = np.zeros(len(hashes), np.int64)
    if len(common):
        leading = hashes & np.uint64(LEADING)
        at = np.minimum(np.searchsorted(common, leading), len(common) - 1)
        rank = np.where(common[at] & np.uint64(LEADING) == leading, counts[at], 0)
    keep = len(hashes) - math.ceil(similarity * len(hashes) - 1e-9) + 1
    return hashes[np.lexsort((hashes, rank))[:keep]]


def parities(hashes: np.ndarray) -> list[int]:
    """PARITIES of a set. Each item that only one of two sets has flips one bit, so sets differ in as many items as bits at least."""
    odd = np.bincount((hashes & np.uint64(255)).astype(np.int64), minlength=256).astype(np.uint8) & 1
    return np.packbits(odd).view(np.int64).tolist()


def word_prints(docs: DataFrame, words: int, similarity: float) -> DataFrame:
    """(doc_id, fp, size, prefix, p0 .. p3): the fingerprint of the distinct words of every row, and of its distinct shingles the number,
    the ``prefix`` and the parities."""
    common, counts = common_shingles(docs, words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps, sizes, first, odd = [], [], [], []
            for text in batch.column(1):
                found = ascii_words(text.as_py())
                shingles = np.unique(shingle_hashes(found, words))
                fps.append(majority(shingle_hashes([*set(found)], 1)))
                sizes.append(len(shingles))
                first.append(prefix(shingles, common, counts, similarity).view(np.int64))
                odd.append(parities(shingles))
            columns = [batch.column(0), pa.array(fps, pa.int64()), pa.array(sizes, pa.int64()), pa.array(first, pa.list_(pa.int64()))]
            columns += [pa.array([x[i] for x in odd], pa.int64()) for i in range(len(PARITIES))]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "fp", "size", "prefix", *PARITIES])

    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return rows.mapInArrow(run, "doc_id long, fp long, size long, prefix array<long>, " + ", ".join(f"{c} long" for c in PARITIES))


def crowd_of(everyone: DataFrame, radius: int) -> DataFrame:
    """(bucket, rep, fp): every row under every mask, where two rows or more share the bucket."""
    entries = buckets(everyone, radius).select("bucket", "rep", "fp")
    return stage(entries.join(stage(crowded(entries).select("bucket"), "crowded"), "bucket"), "crowd")


def led_pairs(crowd: DataFrame, radius: int, turn: int) -> DataFrame:
    """Candidates (a, b): each row with one leader within the radius, the nearest; a bucket's leader is the row that this turn's hash
    chooses. There are never more pairs than rows, and joins make one row for each of the crowd at most."""
    drawn = F.struct(F.xxhash64(F.lit(turn), "rep").alias("h"), "rep", "fp")
    leaders = crowd.groupBy("bucket").agg(F.min(drawn).alias("l"))
    led = crowd.join(leaders, "bucket").select("rep", "l.h", F.col("l.rep").alias("leader"), distance(F.col("fp"), F.col("l.fp")).alias("d"))
    near = led.where((F.col("rep") != F.col("leader")) & (F.col("d") <= radius))
    return near.groupBy("rep").agg(F.min(F.struct("d", "h", "leader"))["leader"].alias("leader")).select(F.col("leader").alias("a"), F.col("rep").alias("b"))


def few(rows: DataFrame, most: int = 300_000) -> DataFrame:
    """``rows`` of a fixed few bytes, marked for broadcasting if there are at most ``most`` of them."""
    return F.broadcast(rows) if rows.limit(most + 1).count() <= most else rows


def ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def labelled(rows: DataFrame, joined: DataFrame) -> DataFrame:
    """``rows`` with ``of``, the component of rep: itself where it has no link."""
    return rows.join(joined.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("of", F.coalesce("component", "rep")).drop("component")


def divided(entries: DataFrame) -> DataFrame:
    """The entries, with their number n, of the shingles that rows of different components share."""
    kinds = entries.groupBy("shingle").agg(F.min("of").alias("lo"), F.max("of").alias("hi"), F.count(F.lit(1)).alias("n")).where("lo < hi").select("shingle", "n")
    return entries.join(stage(kinds, "kinds"), "shingle")


def told_apart(entries: DataFrame) -> DataFrame:
    """The entries of one shingle of all that the same rows hold, which would only give the same pairs again: the first in the order of all
    shingles, at which most of every row is left. Sets of rows are compared by two 64-bit hashes and their number."""
    holders = [F.bit_xor(F.xxhash64(F.lit(i), "rep")).alias(f"h{i}") for i in range(2)]
    kinds = entries.groupBy("shingle", "n").agg(*holders, F.sum("rest").alias("left"))
    first = kinds.groupBy("n", "h0", "h1").agg(F.max(F.struct("left", "shingle"))["shingle"].alias("shingle"))
    return entries.join(stage(first.select("shingle"), "first"), "shingle")


def within(similarity: float) -> Column:
    """Whether a pair can have the similarity if the entries a and b are those of the first shingle that its prefixes share: ``rest``
    counts the shingles from there on, and the parities tell how many at least aren't shared. It bounds the sizes as well."""
    sizes = F.col("a.size") + F.col("b.size")
    apart = sum((distance(F.col(f"a.{p}"), F.col(f"b.{p}")) for p in PARITIES), F.lit(0))
    return (F.least("a.rest", "b.rest") >= similarity / (1 + similarity) * sizes - 1e-9) & (apart <= (1 - similarity) / (1 + similarity) * sizes + 1e-9)


def prefix_led(entries: DataFrame, known: DataFrame, similarity: float, turn: int, leaders: int = 4) -> DataFrame:
    """Candidates (a, b) that aren't ``known``: each row with up to ``leaders`` leaders of other components, those that share the most of its prefix.

    A shingle's leaders are the first and the last of its rows in two orders by this turn's hashes, so that most of them lie in its most
    frequent components and what is left outside meets these. There are as many pairs as rows times ``leaders`` at most, and joins make
    four rows for each entry.
    """
    carried = ["of", "size", "rest", *PARITIES]
    orders = [F.struct(F.xxhash64(F.lit(turn), F.lit(i), "rep").alias("h"), "rep", *carried) for i in range(2)]
    ends = entries.groupBy("shingle").agg(F.array(*[pick(o) for o in orders for pick in (F.min, F.max)]).alias("ends"))
    met = entries.join(ends, "shingle").select(F.struct("rep", *carried).alias("a"), F.explode("ends").alias("b"))
    shared = met.where((F.col("a.of") != F.col("b.of")) & within(similarity)).groupBy(F.col("a.rep").alias("rep"), F.col("b.rep").alias("leader")).agg(F.count(F.lit(1)).alias("k"))
    new = shared.withColumns({"a": F.least("rep", "leader"), "b": F.greatest("rep", "leader")}).join(known, ["a", "b"], "left_anti")
    best = new.groupBy("rep").agg(F.slice(F.sort_array(F.collect_list(F.struct("k", "a", "b")), False), 1, leaders).alias("x"))
    return best.select(F.explode("x").alias("x")).select("x.a", "x.b").distinct()


def prefix_pairs(entries: DataFrame, similarity: float) -> DataFrame:
    """All candidates (a, b) that share a prefix shingle and are in different components.

    Rows outside a shingle's most frequent component meet all its rows, so that a large component is never paired with itself.
    """
    sizes = entries.groupBy("shingle", "of").agg(F.count(F.lit(1)).alias("k"))
    tops = stage(sizes.groupBy("shingle").agg(F.max(F.struct("k", "of"))["of"].alias("top")), "tops")
    few = entries.join(tops, "shingle").where("of <> top")
    once = (F.col("b.of") == F.col("a.top")) | (F.col("a.rep") < F.col("b.rep"))
    both = few.alias("a").join(entries.alias("b"), "shingle").where((F.col("a.of") != F.col("b.of")) & once & within(similarity))
    return ordered(both.select(F.col("a.rep").alias("a"), F.col("b.rep").alias("b")))


def near_duplicates(docs: DataFrame, words: int = 5, similarity: float = 0.8, radius: int = 4, turns: int = 2, prefix_turns: int = 2, pair_up: int = 8) -> DataFrame:
    """(doc_id, component_id) of the documents in a near-duplicate group of two or more; groups are named by their least id.

    A pair is linked if the sets of its ``words``-word shingles have a Jaccard similarity of ``similarity`` or more; every such pair ends
    in one group. Fingerprints of the distinct words come first: rows meet under covering masks of ``radius`` bits, and in each turn a row is
    compared with one leader of its buckets, the nearest; linked rows are merged and the least of them stays for the next of ``turns`` turns.
    The rest is found by prefixes of the shingle sets: two sets of the similarity share a shingle of their prefixes, so all pairs that do
    and are still in different components are compared, at once where ``pair_up`` rows at most share the shingle, and elsewhere after up to
    ``prefix_turns`` turns in which each row meets a few leaders. The exact similarity decides throughout. Rows without an id are left out; repeated rows count once; texts without words are alike; an empty table
    gives no rows.
    """
    repeated = not docs.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").isEmpty()
    drawn = word_prints(docs.where("doc_id is not null"), words, similarity).withColumnRenamed("doc_id", "rep")
    if repeated:
        drawn = drawn.groupBy("rep").agg(F.min(F.struct("fp", "size", "prefix", *PARITIES)).alias("x")).select("rep", "x.*")
    drawn = stage(drawn, "word-prints")

    def alike(pairs: DataFrame) -> DataFrame:
        with scratch(docs.sparkSession):
            ids = few(stage(pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct(), "compared"))
            sets = shingle_sets(docs.select("doc_id", "text").join(ids, "doc_id", "left_semi"), words)
            sets = stage(sets.dropDuplicates(["id"]) if repeated else sets, "shingles")
            both = pairs.join(sets.withColumnsRenamed({"id": "a", "shingles": "sa"}), "a").join(sets.withColumnsRenamed({"id": "b", "shingles": "sb"}), "b")
            common, total = F.size(F.array_intersect("sa", "sb")), F.size("sa") + F.size("sb")
            return stage(both.where((total == 0) | (common >= similarity * (total - common))).select("a", "b"), "links", keep=True)

    crowd = crowd_of(drawn.select("rep", "fp"), radius)
    known = links = drawn.select(F.col("rep").alias("a"), F.col("rep").alias("b")).limit(0)
    joined = components(links)
    for turn in range(turns):
        pairs = stage(ordered(led_pairs(crowd, radius, turn)).join(known, ["a", "b"], "left_anti"), "pairs")
        found = alike(pairs)
        known, links = known.union(pairs), links.union(found)
        if found.isEmpty():
            break
        joined = components(links)
        crowd = stage(crowd.join(few(joined.where("node <> component").select(F.col("node").alias("rep"))), "rep", "left_anti"), "crowd")
    placed = labelled(drawn.select("rep", "size", "prefix"), few(joined)).select("rep", "of", "size", F.posexplode("prefix").alias("at", "shingle"))
    entries = divided(placed.select("shingle", "rep", "of", (F.col("size") - F.col("at")).alias("rest")))
    entries = told_apart(stage(entries, "divided"))
    entries = stage(entries.join(drawn.select("rep", "size", *PARITIES), "rep"), "entries")
    rare, entries = entries.where(F.col("n") <= pair_up), entries.where(F.col("n") > pair_up)
    for turn in range(prefix_turns + 2):
        if turn == 0:
            pairs = prefix_pairs(rare, similarity).join(known, ["a", "b"], "left_anti")
        elif turn <= prefix_turns:
            pairs = prefix_led(entries, known, similarity, turn)
        else:
            pairs = prefix_pairs(entries, similarity).join(known, ["a", "b"], "left_anti")
        pairs = stage(pairs, "pairs")
        found = alike(pairs)
        known, links = known.union(pairs), links.union(found)
        if not found.isEmpty():
            joined = components(links)
            if turn <= prefix_turns:
                entries = stage(divided(labelled(entries.drop("n", "of"), few(joined))), "entries")
    return joined.select(F.col("node").alias("doc_id"), F.col("component").alias("component_id"))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs``, all columns, without those of a near-duplicate group that aren't its least id."""
    with scratch(docs.sparkSession):
        dropped = stage(near_duplicates(docs, **options).where("doc_id <> component_id").select(F.col("doc_id").alias("__id")), "dropped", keep=True)
    return docs.join(dropped, F.col("doc_id") == F.col("__id"), "left_anti")
