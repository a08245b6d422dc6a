"""Helpers that several operators share: word patterns, crc folds, class joins, samples, and the library's staged tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seqstat.sources.tables import scratch, shared_folder, stage

#: The contracts' white space and word patterns (valid in Java, RE2 and Python).
SPACES = r"[\x20\x09-\x0D]+"
WORDS = r"[^\x20\x09-\x0D]+"

def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def fold(doc_id: Column, n: int) -> Column:
    """crc32 of the id as text, modulo n; null ids fall in fold 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % n, F.lit(0)).cast("int")


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def attach_class(rows: DataFrame, key: str, classes: DataFrame, row_id: str, salts: int = 4096) -> DataFrame:
    """Join ``classes`` (one row per ``key``) to ``rows``, of which one key may hold a third.

    Rows are keyed by (key, salt of row_id); the classes are first spread over the pairs that occur,
    at most ``salts`` for a key, so that no single task gets all rows of a hot key.
    """
    salted = rows.withColumn("__salt", F.pmod(F.xxhash64(row_id), F.lit(salts)))
    pairs = salted.groupBy(key, "__salt").agg(F.lit(1).alias("__one")).drop("__one")
    spread = pairs.join(classes, key)
    return salted.join(spread, [key, "__salt"]).drop("__salt")


def sample_rows(df: DataFrame, n: int, seed: int, key: str = "doc_id") -> list:
    """The ``n`` rows with the smallest seeded hash of ``key``: a bounded, repeatable sample for fitting models.

    A threshold on the hash, set from the number of rows, comes first: else every task would send its own ``n`` rows to the
    driver. It lets twice ``n`` rows through on average, so that fewer than ``n`` are left hardly ever.
    """
    drawn = F.pmod(F.xxhash64(F.lit(seed), key), F.lit(1 << 40))
    share = min(1.0, (2 * n + 64) / max(1, df.count()))
    return df.where(drawn <= int(share * (1 << 40))).orderBy(drawn, key).limit(n).collect()


def ascii_words(text: str | None) -> list[bytes]:
    """Words of the contract's pattern, A-Z lowered: bytes.split() splits on exactly x20 and x09-x0D."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()




__all__ = ["SPACES", "WORDS", "ascii_words", "attach_class", "documents", "fold", "sample_rows", "scratch", "shared_folder", "stage", "word_count"]
