"""Level-wise scan: one pass over the corpus per length, pruned with the frequent grams one term shorter (a baseline)."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqstat.operators import candidate_kernel
from seqstat.operators.encode import Prepared
from seqstat.sources.tables import scratch, stage

#: Below so many grams a level is sent to all executors under dictionary='auto'.
BROADCAST_GRAMS = 1_000_000
#: Bytes of windows (uncompressed) that cross an exchange in one turn.
TURN_BYTES = 2 << 30
#: Parts over which the grams that begin candidates of one overlap are dealt, as a common term overlaps many.
SALTS = 8
#: Bits for each gram of the lossy dictionary, and hash functions.
BLOOM_BITS, BLOOM_HASHES = 10, 4


def level_one(p: Prepared, tau: int) -> DataFrame:
    return p.dictionary.where(F.col("cf") >= tau).select(F.array("id").alias("ids"), "cf")


def windows(runs: DataFrame, k: int, *carry: str) -> DataFrame:
    """(pos, ids) of all runs of k terms."""
    long = runs.where(F.size("ids") >= k)
    starts = long.select(*carry, "pos", "ids", F.explode(F.sequence(F.lit(1), F.size("ids") - (k - 1))).alias("__i"))
    return starts.select(*carry, (F.col("pos") + F.col("__i") - 1).alias("pos"), F.slice("ids", F.col("__i"), F.lit(k)).alias("ids"))


def bloom_filter(level: DataFrame):
    """A function that keeps the rows of which all the given parts are grams of ``level``, and few others."""
    size = max(64, BLOOM_BITS * level.count())
    places = level.select(F.explode(F.array(*[F.pmod(F.xxhash64(F.lit(s), F.col("ids")), F.lit(size)) for s in range(BLOOM_HASHES)])).alias("at"))

    def bits(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        mine = np.zeros((size + 7) // 8, np.uint8)
        for batch in batches:
            at = batch["at"].to_numpy()
            np.bitwise_or.at(mine, at // 8, (1 << (at % 8)).astype(np.uint8))
        used = np.flatnonzero(mine)
        yield pd.DataFrame({"byte": used, "bits": mine[used].astype(np.int64)})

    whole = np.zeros((size + 7) // 8, np.uint8)
    for row in places.mapInPandas(bits, "byte long, bits long").groupBy("byte").agg(F.bit_or("bits").alias("bits")).toLocalIterator():
        whole[row["byte"]] = row["bits"]
    sent = level.sparkSession.sparkContext.broadcast(whole)

    def passed(rows: DataFrame, *parts: Column) -> DataFrame:
        """A pass over batches: a Python column function would queue whole rows on disk while it runs."""
        hashes = [F.pmod(F.xxhash64(F.lit(s), part), F.lit(size)) for part in parts for s in range(BLOOM_HASHES)]
        names, number = rows.columns, len(hashes)
        asked = rows.select(*names, *[h.alias(f"__h{i}") for i, h in enumerate(hashes)])

        def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            filled = sent.value
            for batch in batches:
                hit = np.ones(batch.num_rows, bool)
                for i in range(number):
                    at = batch.column(f"__h{i}").to_numpy()
                    hit &= (filled[at // 8] >> (at % 8).astype(np.uint8)) & 1 == 1
                yield batch.select(names).filter(pa.array(hit))

        return asked.mapInArrow(probe, rows.schema)

    return passed


def parts_of(k: int) -> tuple[Column, Column]:
    """A gram's first and last k-1 terms."""
    return F.slice("ids", F.lit(1), F.lit(k - 1)), F.slice("ids", F.lit(2), F.lit(k - 1))


def prune(rows: DataFrame, level: DataFrame, k: int, dictionary: str) -> DataFrame:
    """Rows whose first and last k-1 terms are both grams of ``level``."""
    head, tail = parts_of(k)
    if dictionary == "bloom":
        return bloom_filter(level)(rows, head, tail)
    if dictionary == "auto":
        dictionary = "broadcast" if level.limit(BROADCAST_GRAMS + 1).count() <= BROADCAST_GRAMS else "shuffle"
    for part, name in ((head, "__head"), (tail, "__tail")):
        side = level.select(F.col("ids").alias(name))
        side = F.broadcast(side) if dictionary == "broadcast" else side.hint("merge" if dictionary == "merge" else "shuffle_hash")
        rows = rows.join(side, part == F.col(name), "left_semi")
    return rows


def overlapping(level: DataFrame, k: int, lefts: DataFrame | None = None, runs: DataFrame | None = None, turn: int = 0, turns: int = 1) -> tuple[DataFrame, list[str]]:
    """Rows (overlap, salt, kind, word), sorted, and the overlap's columns, which are the k-2 terms between the first and the last of a candidate. Grams
    that begin one (``lefts``) and windows of ``runs`` are dealt over turns and salts by their first term; grams that end one go to all. Where the
    level is small enough to be sent to all executors, windows that no candidate begins like stay where they are."""
    names = [f"o{j}" for j in range(k - 2)]
    dealt = lambda first: F.pmod(F.xxhash64(first), F.lit(SALTS * turns)).cast("int")
    high = lambda first: F.shiftleft(first.cast("long"), 32)
    ids, at = F.col("ids"), F.col("__i")

    def rows(df: DataFrame, shift, kind: int, word: Column, first: Column | None = None) -> DataFrame:
        if first is not None and turns > 1:
            df = df.where(dealt(first) % turns == turn)
        salt = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))) if first is None else (dealt(first) / turns).cast("int")
        return df.select(*[ids[shift + j].alias(n) for j, n in enumerate(names)], salt.alias("salt"), F.lit(kind).alias("kind"), word.alias("word"))

    found = rows(level if lefts is None else lefts, 1, candidate_kernel.LEFT, high(ids[0]), ids[0])
    found = found.unionByName(rows(level, 0, candidate_kernel.RIGHT, ids[k - 2].cast("long")))
    if runs is not None:
        starts = runs.where(F.size("ids") >= k).select("ids", F.explode(F.sequence(F.lit(0), F.size("ids") - k)).alias("__i"))
        seen = rows(starts, at + 1, candidate_kernel.WINDOW, high(ids[at]).bitwiseOR(ids[at + (k - 1)].cast("long")), ids[at])
        if level.limit(BROADCAST_GRAMS + 1).count() <= BROADCAST_GRAMS:
            heads = (level if lefts is None else lefts).select(ids[0].alias("first"), *[ids[1 + j].alias(n) for j, n in enumerate(names)])
            seen = seen.withColumn("first", F.shiftright("word", 32).cast("int")).join(F.broadcast(heads), ["first", *names], "left_semi").drop("first")
        found = found.unionByName(seen)
    return found.repartition(*names, "salt").sortWithinPartitions(*names, "salt", "kind", "word"), names


def generated(level: DataFrame, k: int, lefts: DataFrame | None = None) -> DataFrame:
    """All k-grams that two overlapping grams of ``level`` make, seen or not (a control: too many candidates); ``lefts`` are those that may begin one."""
    rows, names = overlapping(level, k, lefts)
    return rows.mapInArrow(lambda batches: candidate_kernel.made(batches, names), "ids array<int>")


def generated_number(level: DataFrame, k: int) -> int:
    """How many k-grams ``generated`` makes, from the number of grams on either side of each overlap."""
    sides = [level.groupBy(F.slice("ids", F.lit(at), F.lit(k - 2)).alias("o")).agg(F.count(F.lit(1)).alias(name)) for at, name in ((2, "l"), (1, "r"))]
    return sides[0].join(sides[1], "o").agg(F.sum(F.col("l") * F.col("r"))).first()[0] or 0


def counted_generated(p: Prepared, level: DataFrame, k: int, tau: int, turn_bytes: int = TURN_BYTES) -> DataFrame:
    """(ids, cf) of the frequent ones of all generated k-grams. Candidates are made where the windows of their overlap are, as words, so that none
    crosses an exchange. Beyond ``turn_bytes`` of windows first terms are dealt over turns, each written before the next one starts."""
    windows_number = p.runs.agg(F.sum(F.greatest(F.size("ids") - (k - 1), F.lit(0)))).first()[0] or 0
    turns = max(1, -(-windows_number * 8 * (k + 2) // turn_bytes))
    parts = []
    for t in range(turns):
        with scratch(p.runs.sparkSession):
            rows, names = overlapping(level, k, None, p.runs, t, turns)
            found = rows.mapInArrow(lambda batches, names=names: candidate_kernel.counted(batches, names, tau), "ids array<int>, cf long")
            parts.append(stage(found, "turn", keep=True))
            del rows, found
    return reduce(DataFrame.unionByName, parts)


def counted_bloom(p: Prepared, level: DataFrame, k: int, tau: int, turn_bytes: int = TURN_BYTES) -> DataFrame:
    """(ids, cf) of the frequent ones of the windows that the filter of ``level`` lets through. Beyond ``turn_bytes`` of windows their first terms
    are dealt over turns, each written before the next one starts; the shuffle files of the filter and of a turn go when it ends."""
    windows_number = p.runs.agg(F.sum(F.greatest(F.size("ids") - (k - 1), F.lit(0)))).first()[0] or 0
    turns = max(1, -(-windows_number * (24 + 4 * k) // turn_bytes))
    known, parts = bloom_filter(level) if k > 2 else None, []
    for t in range(turns):
        with scratch(p.runs.sparkSession):
            rows = windows(p.runs, k)
            rows = rows.where(F.pmod(F.xxhash64(F.col("ids")[0]), F.lit(turns)) == t) if turns > 1 else rows
            rows = known(rows.select("ids"), *parts_of(k)) if known else rows
            parts.append(stage(rows.groupBy("ids").agg(F.count(F.lit(1)).alias("cf")).where(F.col("cf") >= tau), "turn", keep=True))
            del rows
    return reduce(DataFrame.unionByName, parts)


def carried(rows: DataFrame, k: int) -> DataFrame:
    """Survivors (doc_id, pos, ids) of k-1 terms that stand side by side, as k-grams: the corpus isn't read again."""
    order = Window.partitionBy("doc_id").orderBy("pos")
    ahead = rows.withColumn("__pos", F.lead("pos").over(order)).withColumn("__ids", F.lead("ids").over(order))
    joined: Column = F.concat("ids", F.slice("__ids", F.lit(k - 1), F.lit(1)))
    return ahead.where(F.col("__pos") == F.col("pos") + 1).select("doc_id", "pos", joined.alias("ids"))


def levels(p: Prepared, tau: int, sigma: int | None, dictionary: str = "auto", candidates: str = "observed", carry_survivors: bool = False) -> Iterator[tuple[int, DataFrame]]:
    """(k, level) until sigma or an empty level; each level is written before the next round reads it."""
    level, k = stage(level_one(p, tau), "level"), 1
    kept = None
    while sigma is None or k <= sigma:
        if level.isEmpty():
            return
        yield k, level
        k += 1
        if sigma is not None and k > sigma:
            return
        if carry_survivors:
            rows = windows(p.runs, 2, "doc_id") if k == 2 else carried(kept, k)
            rows = stage(rows.select("doc_id", "pos", "ids"), "candidates")
        elif candidates == "generated" and k > 2:
            level = counted_generated(p, level, k, tau)
            continue
        elif dictionary == "bloom":
            level = counted_bloom(p, level, k, tau)
            continue
        else:
            rows = windows(p.runs, k)
            rows = prune(rows, level, k, dictionary) if k > 2 else rows
        level = stage(rows.groupBy("ids").agg(F.count(F.lit(1)).alias("cf")).where(F.col("cf") >= tau), "level")
        if carry_survivors:
            kept = stage(rows.join(level.select("ids"), "ids", "left_semi"), "survivors")


def levelwise_scan(p: Prepared, tau: int, sigma: int | None, dictionary: str = "auto", candidates: str = "observed", carry_survivors: bool = False) -> DataFrame:
    """(ids, cf). dictionary: broadcast, shuffle, merge (spilling), bloom or auto."""
    found = [level for _, level in levels(p, tau, sigma, dictionary, candidates, carry_survivors)]
    return reduce(DataFrame.unionByName, found) if found else level_one(p, tau).where("false")
