"""Dictionaries, integer encoding, and splits at rare terms.

A prepared corpus ("runs") has doc_id, seq_no, pos, ids ARRAY<INT> and any meta columns: maximal stretches of frequent terms,
each at the position of its first term, so that a removed term leaves a gap.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A dictionary of more terms or bytes than this isn't sent to all executors; it is joined instead.
BROADCAST_TERMS, BROADCAST_BYTES = 1_000_000, 32 << 20


@dataclass(frozen=True)
class Options:
    """Switches that all methods share; each is one of the techniques whose effect the ablations measure."""

    split_rare: bool = True
    local_combine: bool = False
    partitioner: str = "range"
    partitions: int | None = None
    kernel: str = "vector"
    how: str = "auto"


@dataclass
class Prepared:
    """Runs of ids and the dictionary (term, id, cf) of the terms in them."""

    runs: DataFrame
    dictionary: DataFrame
    meta: list[str]


def term_counts(corpus: DataFrame) -> DataFrame:
    # An inner explode would bring a filter on the size of ``terms``, for which they are found a second time.
    return corpus.select(F.explode_outer("terms").alias("term")).where(F.col("term").isNotNull()).groupBy("term").agg(F.count(F.lit(1)).alias("cf"))


def build_dictionary(corpus: DataFrame, tau: int = 1) -> DataFrame:
    """(term, id, cf): ids from 1 by descending cf, ties by term, for terms of cf >= tau.

    Terms are range-sorted; only the partitions' sizes reach the driver, and a term's id is its partition's offset plus its
    place: no single task sees all terms.
    """
    from seqstat.sources.tables import stage

    counted = term_counts(corpus).where(F.col("cf") >= tau)
    parts = counted.repartitionByRange(F.col("cf").desc(), F.col("term")).sortWithinPartitions(F.col("cf").desc(), "term")
    placed = stage(parts.withColumn("__at", F.monotonically_increasing_id()), "terms")
    part = F.shiftright("__at", 33).cast("int")
    sizes = {r["part"]: r["count"] for r in placed.groupBy(part.alias("part")).count().collect()}
    starts, total = [], 0
    for p in sorted(sizes):
        starts += [F.lit(p), F.lit(total)]
        total += sizes[p]
    if not starts:
        return placed.select("term", F.lit(0).alias("id"), "cf")
    offset = F.create_map(*starts)[part]
    return placed.select("term", (offset + F.col("__at").bitwiseAND((1 << 33) - 1) + 1).cast("int").alias("id"), "cf")


def encode(corpus: DataFrame, dictionary: DataFrame, how: str = "auto") -> DataFrame:
    """Runs of the dictionary's terms; terms that it lacks are barriers (all kept where it has all terms).

    'arrow' sends the dictionary to all executors and looks up whole batches; 'join' explodes, joins and regroups, for
    dictionaries beyond BROADCAST_TERMS or BROADCAST_BYTES; 'auto' measures first.
    """
    meta = [c for c in corpus.columns if c not in ("doc_id", "seq_no", "pos", "terms")]
    if how == "auto":
        terms, octets = dictionary.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("term")), F.lit(0))).first()
        how = "arrow" if terms <= BROADCAST_TERMS and octets <= BROADCAST_BYTES else "join"
    return _by_lookup(corpus, dictionary, meta) if how == "arrow" else _by_join(corpus, dictionary, meta)


def _by_lookup(corpus: DataFrame, dictionary: DataFrame, meta: list[str]) -> DataFrame:
    table = dictionary.select("term", "id").toArrow()
    sent = corpus.sparkSession.sparkContext.broadcast((table["term"].to_pylist(), table["id"].to_pylist()))
    source = corpus.select("doc_id", "seq_no", "pos", "terms", *meta)
    fields = [f for f in source.schema.fields if f.name != "terms"]
    schema = T.StructType([*fields, T.StructField("ids", T.ArrayType(T.IntegerType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = dict(zip(*sent.value, strict=True))  # once a task; a batch looks up its distinct terms
        for batch in batches:
            column = batch.column("terms")
            flat = column.flatten().fill_null("").dictionary_encode()
            own = np.fromiter((known.get(t, 0) for t in flat.dictionary.to_pylist()), np.int32, len(flat.dictionary))
            found = own[flat.indices.to_numpy()] if len(flat) else np.zeros(0, np.int32)
            offsets = column.offsets.to_numpy() - column.offsets[0].as_py()
            row = np.repeat(np.arange(batch.num_rows), np.diff(offsets))
            kept = np.flatnonzero(found)  # ids begin at 1
            first = np.ones(len(kept), bool)
            first[1:] = (np.diff(kept) > 1) | (np.diff(row[kept]) > 0)
            starts = np.flatnonzero(first)
            rows = row[kept[starts]]
            lists = pa.ListArray.from_arrays(pa.array(np.append(starts, len(kept)), pa.int32()), pa.array(found[kept]))
            columns = []
            for f in fields:
                taken = batch.column(f.name).take(pa.array(rows, pa.int64()))
                columns.append(pc.add(taken, pa.array(kept[starts] - offsets[rows], pa.int64())) if f.name == "pos" else taken)
            yield pa.RecordBatch.from_arrays([*columns, lists], [*[f.name for f in fields], "ids"])

    return source.mapInArrow(run, schema)


def _by_join(corpus: DataFrame, dictionary: DataFrame, meta: list[str]) -> DataFrame:
    # Sequences are numbered, as those of two tables may agree in document and position.
    others = ["doc_id", "seq_no", *meta]
    flat = corpus.withColumn("__row", F.monotonically_increasing_id()).select("__row", *others, "pos", F.posexplode("terms").alias("__i", "term"))
    known = flat.join(dictionary.select("term", "id"), "term").withColumn("__p", F.col("pos") + F.col("__i"))
    order = Window.partitionBy("__row").orderBy("__i")
    islands = known.withColumn("__run", F.col("__i") - F.row_number().over(order))
    ids = F.sort_array(F.collect_list(F.struct("__i", "id")))["id"].alias("ids")
    grouped = islands.groupBy("__row", "__run").agg(F.min("__p").alias("pos"), ids, *[F.first(c).alias(c) for c in others])
    return grouped.select("doc_id", "seq_no", "pos", *meta, "ids")


def prepare(corpus: DataFrame, tau: int, opts: Options = Options()) -> Prepared:
    """Dictionary and runs, written once: every method and every round reads them from there."""
    from seqstat.sources.tables import stage

    meta = [c for c in corpus.columns if c not in ("doc_id", "seq_no", "pos", "terms")]
    dictionary = stage(build_dictionary(corpus, tau if opts.split_rare else 1), "dictionary")
    return Prepared(stage(encode(corpus, dictionary, opts.how), "runs"), dictionary, meta)


def decode(stats: DataFrame, dictionary: DataFrame, key: str = "ids", name: str = "gram", broadcast_terms: int = 200_000) -> DataFrame:
    """Replace the id array ``key`` by the terms joined by one space, in column ``name``; other columns stay."""
    others = [c for c in stats.columns if c != key]
    small = dictionary.limit(broadcast_terms + 1).count() <= broadcast_terms
    if small:
        words = dict(dictionary.select("id", "term").toArrow().to_pandas().itertuples(index=False))
        sent = stats.sparkSession.sparkContext.broadcast(np.array([words.get(i, "") for i in range(max(words, default=0) + 1)], object))
        schema = T.StructType([T.StructField(name, T.StringType()), *[f for f in stats.schema.fields if f.name != key]])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                column = batch.column(key)
                flat = pa.array(sent.value[column.flatten().to_numpy()], pa.string())
                offsets = pc.subtract(column.offsets, column.offsets[0])
                joined = pc.binary_join(pa.ListArray.from_arrays(offsets, flat), " ")
                yield pa.RecordBatch.from_arrays([joined, *[batch.column(c) for c in others]], [name, *others])

        return stats.mapInArrow(run, schema)
    from seqstat.sources.tables import stage

    # Numbers are written before use: a second evaluation, even of one task that runs again, could number the rows in another order.
    numbered = stage(stats.withColumn("__row", F.monotonically_increasing_id()), "numbered")
    flat = numbered.select("__row", *others, F.posexplode_outer(key).alias("__i", "id")).join(dictionary.select("id", "term"), "id", "left")
    term = F.struct("__i", F.coalesce("term", F.lit("")).alias("term"))
    names = flat.groupBy("__row").agg(F.array_join(F.sort_array(F.collect_list(term))["term"], " ").alias(name), *[F.first(c).alias(c) for c in others])
    return names.select(name, *others)


def varbyte_size(ids: Column) -> Column:
    """Bytes of an id array in 7-bit groups."""
    one = lambda i: F.when(i < 1 << 7, 1).when(i < 1 << 14, 2).when(i < 1 << 21, 3).when(i < 1 << 28, 4).otherwise(5)
    return F.aggregate(ids, F.lit(0).cast("long"), lambda s, i: s + one(i))


def sort_key(ids: Column) -> Column:
    """Big-endian bytes of positive ids: binary order is the order of the arrays."""
    return F.unhex(F.array_join(F.transform(ids, lambda i: F.lpad(F.hex(i), 8, "0")), ""))
