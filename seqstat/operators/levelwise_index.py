"""Level-wise index: postings of frequent grams up to K terms, then joins of compatible postings (a baseline)."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqstat.operators.direct import gram_rows
from seqstat.operators.encode import Prepared
from seqstat.operators.levelwise_scan import BROADCAST_GRAMS, windows
from seqstat.sources.tables import stage


#: What a gram that two entries make is known by.
PAIR = ("ahead", "left", "right")
#: Lists of at least so many terms meet at all distances up to their length, so that the rounds follow the logarithm of sigma.
LEAP_TERMS = 4


def places(runs: DataFrame, k: int) -> tuple[DataFrame, list[str]]:
    """(doc_id, pos, t0, ...) of all windows of k terms, a column for each term, and the names of these columns."""
    names = [f"t{i}" for i in range(k)]
    starts = runs.where(F.size("ids") >= k).select("doc_id", "pos", "ids", F.explode(F.sequence(F.lit(0), F.size("ids") - k)).alias("__i"))
    return starts.select("doc_id", (F.col("pos") + F.col("__i")).alias("pos"), *[F.col("ids")[F.col("__i") + i].alias(n) for i, n in enumerate(names)]), names


def frequent_places(runs: DataFrame, k: int, tau: int) -> DataFrame:
    """(ids, cf) of the frequent grams of k terms, counted by a column for each term: keys of fixed width are hashed faster than arrays."""
    rows, keys = places(runs, k)
    often = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("cf")).where(F.col("cf") >= tau)
    return often.select(F.array(*keys).alias("ids"), "cf")


def numbered(rows: DataFrame, tau: int, *keys: str) -> DataFrame:
    """(keys, cf) of the grams of ``rows`` with cf >= tau, each with a number, ``gram``: to be written before use, as numbers are drawn anew otherwise."""
    often = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("cf")).where(F.col("cf") >= tau)
    return often.withColumn("gram", F.monotonically_increasing_id())


def frequent(rows: DataFrame, tau: int) -> DataFrame:
    """(ids, cf, gram) of the frequent grams, written once."""
    return stage(numbered(rows, tau, "ids"), "often")


def gathered(rows: DataFrame, often: DataFrame, shards: int = 1, small: bool | None = None, keys: Sequence[str] = ("ids",)) -> DataFrame:
    """(gram, shard, plist): the lists of the grams ``often`` over their occurrences. Only numbers cross the network and are sorted; a
    pass over neighbours, with the state of one list, makes the lists. Up to BROADCAST_GRAMS grams (``small``) are sent to all executors."""
    small = often.limit(BROADCAST_GRAMS + 1).count() <= BROADCAST_GRAMS if small is None else small
    sent = F.broadcast if small else lambda df: df
    shard = F.pmod(F.xxhash64("doc_id"), F.lit(shards)).cast("int").alias("shard")
    order = ["gram", "shard", "doc_id", "pos"]
    entries = rows.join(sent(often.select(*keys, "gram")), list(keys)).select("gram", shard, "doc_id", "pos")
    entries = entries.repartition("gram", "shard").sortWithinPartitions(*order)

    def lists(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(parts).combine_chunks()
        gram, part, pos = (table[c].to_numpy() for c in ("gram", "shard", "pos"))
        doc, none = table["doc_id"].fill_null(0).to_numpy(), table["doc_id"].is_null().to_numpy(zero_copy_only=False)
        starts = np.ones(len(gram), bool)
        starts[1:] = (np.diff(gram) != 0) | (np.diff(part) != 0)
        begins = starts.copy()
        begins[1:] |= (np.diff(doc) != 0) | (none[1:] != none[:-1])
        groups, docs = np.flatnonzero(starts), np.flatnonzero(begins)
        positions = pa.ListArray.from_arrays(pa.array(np.append(docs, len(gram)), pa.int32()), pa.array(pos))
        ids = pa.array(doc[docs], mask=none[docs])
        entry = pa.StructArray.from_arrays([ids, positions], ["doc_id", "positions"])
        plist = pa.ListArray.from_arrays(pa.array(np.append(np.searchsorted(docs, groups), len(docs)), pa.int32()), entry)
        return pa.RecordBatch.from_arrays([pa.array(gram[groups]), pa.array(part[groups]), plist], ["gram", "shard", "plist"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = []  # the rows of the last list so far
        for batch in batches:
            if not batch.num_rows:
                continue
            gram, part = batch.column("gram").to_numpy(), batch.column("shard").to_numpy()
            own = int(np.flatnonzero((gram != gram[-1]) | (part != part[-1])).max(initial=-1)) + 1  # where the batch's last list begins
            going = held and held[0].column("gram")[0].as_py() == gram[-1] and held[0].column("shard")[0].as_py() == part[-1]
            if own or (held and not going):
                yield lists([*held, batch.slice(0, own)])
                held = []
            held.append(batch.slice(own))
        if held:
            yield lists(held)

    return entries.mapInArrow(run, "gram long, shard int, plist array<struct<doc_id: long, positions: array<long>>>")


def with_ids(lists: DataFrame, often: DataFrame) -> DataFrame:
    """(ids, shard, plist, cf) of the lists of numbered grams."""
    return lists.join(often.select("gram", "ids", "cf"), "gram").select("ids", "shard", "plist", "cf")


def postings(rows: DataFrame, tau: int, shards: int = 1) -> DataFrame:
    """(ids, shard, plist, cf) from occurrences (ids, doc_id, pos); plist holds (doc_id, positions), cf counts all shards.

    With more shards, a gram's list is cut by document, so that no array follows the corpus; the threshold is on the total. Frequent
    grams are counted first, so that only their occurrences are gathered into lists.
    """
    often = frequent(rows, tau)
    return with_ids(gathered(rows, often, shards), often)


def meet(lists: DataFrame, reach: int = 1, least: int = 1, whole: bool = True) -> DataFrame:
    """(ahead, left, right, doc_id, pos): each entry of the lists (gram, plist) with those that follow it by ``least`` to ``reach`` places, where no place
    between is without an entry. All lists are merged in one exchange by document and position, so the work follows the entries and not the
    pairs of lists; an entry and the one j places on make a gram of j terms more. Without ``whole`` no places are given, for counts."""
    entries = lists.select("gram", F.explode("plist").alias("e")).select("gram", "e.doc_id", F.explode("e.positions").alias("pos"))
    entries = entries.repartition("doc_id").sortWithinPartitions("doc_id", "pos")

    def pairs(gram: np.ndarray, doc: np.ndarray, none: np.ndarray, pos: np.ndarray, starts: int) -> Iterator[pa.RecordBatch]:
        for j in range(least, reach + 1):
            n = min(starts, len(gram) - j)
            if n <= 0:
                return
            at = np.flatnonzero((pos[j : j + n] == pos[:n] + j) & (doc[j : j + n] == doc[:n]) & (none[j : j + n] == none[:n]))
            columns = [pa.array(np.full(len(at), j, np.int32)), pa.array(gram[at]), pa.array(gram[at + j])]
            if whole:
                columns += [pa.array(doc[at], mask=none[at]), pa.array(pos[at])]
            yield pa.RecordBatch.from_arrays(columns, ["ahead", "left", "right", "doc_id", "pos"][: len(columns)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # the last entries, which go on in the next batch
        for batch in batches:
            doc = batch.column("doc_id")
            rows = [batch.column("gram").to_numpy(), doc.fill_null(0).to_numpy(), doc.is_null().to_numpy(zero_copy_only=False), batch.column("pos").to_numpy()]
            held = rows if held is None else [np.concatenate(both) for both in zip(held, rows, strict=True)]
            starts = len(held[0]) - reach
            if starts > 0:
                yield from pairs(*held, starts)
                held = [column[starts:] for column in held]
        if held:
            yield from pairs(*held, len(held[0]))

    return entries.mapInArrow(run, "ahead int, left long, right long" + (", doc_id long, pos long" if whole else ""))


def extended(rows: DataFrame, often: DataFrame, k: int, tau: int) -> DataFrame:
    """(ahead, left, right, cf, gram, ids) of the frequent grams of ``rows`` that meet; ``often`` has those of k terms, which they are made of."""
    found = numbered(rows, tau, "ahead", "left", "right")
    first, last = (often.select(F.col("gram").alias(side), F.col("ids").alias(f"__{side}")) for side in ("left", "right"))
    ids = F.concat("__left", F.slice("__right", k - F.col("ahead") + 1, F.col("ahead"))).alias("ids")
    return stage(found.join(first, "left").join(last, "right").select("ahead", "left", "right", "cf", "gram", ids), "often")


def extend_nested(level: DataFrame, k: int, tau: int, shards: int = 1) -> DataFrame:
    """Postings of the k-grams from those of k-1 terms, level by level and without numbers: one join by document and position."""
    left = level.select("ids", F.explode("plist").alias("e")).select("ids", "e.doc_id", F.explode("e.positions").alias("pos"))
    ahead = left.select("doc_id", (F.col("pos") - 1).alias("pos"), F.col("ids")[k - 2].alias("last"))
    right = ahead.repartition("doc_id", "pos").distinct()
    met = stage(left.join(right, ["doc_id", "pos"]).select(F.concat("ids", F.array("last")).alias("ids"), "doc_id", "pos"), "met")
    return postings(met, tau, shards)


def extend_flat(level: DataFrame, k: int, tau: int) -> DataFrame:
    """The same on occurrences (ids, doc_id, pos): a row joins the one at the next position of its document."""
    right = level.select("doc_id", (F.col("pos") - 1).alias("pos"), F.slice("ids", F.lit(k - 1), F.lit(1)).alias("last"))
    rows = stage(level.join(right, ["doc_id", "pos"]).select(F.concat("ids", "last").alias("ids"), "doc_id", "pos"), "rows")
    frequent = rows.groupBy("ids").count().where(F.col("count") >= tau).select("ids")
    return rows.join(frequent, "ids", "left_semi")


def counted(level: DataFrame) -> DataFrame:
    return level.groupBy("ids").agg(F.count(F.lit(1)).alias("cf"))


def levelwise_index(p: Prepared, tau: int, sigma: int | None, K: int = 4, form: str = "nested", shards: int = 1, positions_below_K: bool = False, seen: Callable[[int, DataFrame], None] | None = None) -> tuple[DataFrame, DataFrame]:
    """(stats, last level). Up to K terms the corpus is read, beyond it the postings are joined, until sigma or an empty level; ``seen``
    is called with each length and level of postings that is joined with itself.

    Grams of k terms that stand j <= k places apart make each gram of k + j terms, so a level of LEAP_TERMS or more gives all lengths up to
    twice its own at once, of which the last one gets lists. Below K only counts are needed, unless positions_below_K; with K = 1 all
    lists would share the empty overlap, so the flat form is taken there.
    """
    form = "flat" if K == 1 else form
    top = K if sigma is None else min(K, sigma)
    found, level = [], None
    if top > 1:
        if positions_below_K:
            found.append(postings(gram_rows(p.runs, top - 1, "doc_id"), tau, shards).groupBy("ids").agg(F.max("cf").alias("cf")))
        else:
            found += [frequent_places(p.runs, n, tau) for n in range(1, top)]
    k = top
    if form == "flat":
        rows = stage(windows(p.runs, top, "doc_id"), "rows")
        level = stage(rows.join(counted(rows).where(F.col("cf") >= tau).select("ids"), "ids", "left_semi"), "level")
        while not level.isEmpty():
            found.append(counted(level))
            k += 1
            if sigma is not None and k > sigma:
                break
            if seen:
                seen(k - 1, level)
            level = stage(extend_flat(level, k, tau), "level")
        return (reduce(DataFrame.unionByName, found) if found else counted(rows).where("false")), level
    rows, keys = places(p.runs, top)
    often = stage(numbered(rows, tau, *keys).withColumn("ids", F.array(*keys)), "often")
    found.append(often.select("ids", "cf"))
    while True:
        n = often.count()
        lists = gathered(rows, often, shards, n <= BROADCAST_GRAMS, keys)
        if not n or k == sigma:  # no list is joined any more: the last ones are made for whoever reads them
            return reduce(DataFrame.unionByName, found), with_ids(lists, often)
        lists = stage(lists, "level")
        if seen:
            seen(k, with_ids(lists, often))
        reach = k if k >= LEAP_TERMS else 1
        reach = reach if sigma is None else min(reach, sigma - k)
        if reach == 1 and k + 1 != sigma:
            rows = stage(meet(lists), "met")
            longer = extended(rows, often, k, tau)
        else:
            longer = extended(meet(lists, reach, whole=False), often, k, tau)
            rows = meet(lists, reach, reach)
        found.append(longer.select("ids", "cf"))
        often, keys, k = longer.where(F.col("ahead") == reach), PAIR, k + reach


def locate(p: Prepared, tau: int, gram: list[str], K: int = 4) -> DataFrame:
    """(doc_id, pos) of one gram if it is frequent, from postings of at most K terms: a longer gram is where its parts stand in a row."""
    ids = p.dictionary.where(F.col("term").isin(*gram)).collect()
    number = {r["term"]: r["id"] for r in ids}
    top = min(K, len(gram))
    lists = postings(windows(p.runs, top, "doc_id"), tau, 16)
    flat = lists.select("ids", F.explode("plist").alias("x")).select("ids", "x.doc_id", F.explode("x.positions").alias("pos"))
    if len(number) < len(set(gram)):
        return flat.select("doc_id", "pos").where("false")
    found = None
    for at in range(0, len(gram) - top + 1):
        part = flat.where(F.col("ids") == F.array(*[F.lit(number[t]) for t in gram[at : at + top]])).select("doc_id", (F.col("pos") - at).alias("pos"))
        found = part if found is None else found.join(part, ["doc_id", "pos"], "left_semi")
    many = found.agg(F.count(F.lit(1)).alias("cf")).where(F.col("cf") >= tau)
    return found.join(F.broadcast(many), F.lit(True)).select("doc_id", "pos")
