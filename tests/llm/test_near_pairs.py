"""Near duplicates by edits in one stretch: every pair at similarity 0.8 or more, against a comparison of all pairs."""

import itertools

import numpy as np
from pyspark.sql import functions as F

from seqstat.llm import simhash


def zipf_words(rng, n):
    return [f"w{x}" for x in np.minimum(rng.zipf(1.3, n), 50_000)]


def plain_groups(rows):
    sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for i, t in rows if (w := t.split())}
    group = {i: i for i in sets}
    for a, b in itertools.combinations(sets, 2):
        if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]) and group[a] != group[b]:
            low, high = sorted((group[a], group[b]))
            group = {i: low if g == high else g for i, g in group.items()}
    return {i: g for i, g in group.items() if list(group.values()).count(g) > 1}


def groups(spark, rows):
    return {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}


def test_passages_appended_cut_and_replaced(spark):
    """Shares of the shingles from 0.80 to 0.90 that the pair keeps, and some pairs just below."""
    rng, rows = np.random.default_rng(8), []
    for i in range(120):
        n = 200 if i % 2 else 500
        words, share = zipf_words(rng, n), (0.79, 0.8, 0.82, 0.85, 0.9)[i % 5]
        extra = int((n - 4) * (1 / share - 1)) + (share < 0.8)
        at = int(rng.integers(0, n - extra))
        half = int((n - 4) * (1 - share) / (1 + share)) - 4
        other = [words + zipf_words(rng, extra), words[: 4 + int((n - 4) * share + 0.999)], words[:at] + zipf_words(rng, half) + words[at + half :], zipf_words(rng, extra) + words][i // 5 % 4]
        rows += [(2 * i, " ".join(words)), (2 * i + 1, " ".join(other))]
    want = plain_groups(rows)
    assert 160 < len(want) < 230
    assert groups(spark, rows) == want


def test_crowd_with_one_body(spark):
    """A hundred texts with one body and an own ending each, and the body itself; others share a line alone."""
    rng = np.random.default_rng(9)
    body, line = zipf_words(rng, 300), [f"line{i}" for i in range(12)]
    rows = [(i, " ".join(body + [f"e{i}.{k}" for k in range(20 + i % 60)])) for i in range(100)] + [(500, " ".join(body))]
    rows += [(600 + i, " ".join(line + [f"o{i}.{k}" for k in range(i % 5)])) for i in range(80)]
    assert groups(spark, rows) == plain_groups(rows)


def test_prefixes_of_near_sets_meet():
    rng = np.random.default_rng(10)
    for _ in range(300):
        pool = rng.integers(0, 1 << 63, 400).astype(np.uint64)
        common = np.unique(pool[::3])
        a = np.unique(pool[: rng.integers(1, 300)])
        b = np.unique(np.concatenate([a[: rng.integers(0, len(a) + 1)], pool[300 : 300 + rng.integers(0, 40)]]))
        both = len(np.intersect1d(a, b))
        if both and both >= 0.8 * (len(a) + len(b) - both):
            counts = common.astype(np.int64) % 7 + 2
            assert len(np.intersect1d(*[simhash.prefix(x, common, counts, 0.8) for x in (a, b)]))


def test_parities_bound_the_difference():
    rng = np.random.default_rng(11)
    for _ in range(200):
        a, b = (np.unique(rng.integers(0, 1 << 20, rng.integers(0, 600)).astype(np.uint64)) for _ in range(2))
        b = np.union1d(b, a[: rng.integers(0, len(a) + 1)])
        bits = sum(((x ^ y) & (1 << 64) - 1).bit_count() for x, y in zip(simhash.parities(a), simhash.parities(b), strict=True))
        assert bits <= len(np.setxor1d(a, b))


def test_border_group_costs_no_pair(spark):
    """Copies of one text with random words changed, around the similarity: many rows are near some of the group and far from the rest."""
    rng = np.random.default_rng(12)
    words, rows = zipf_words(rng, 150), []
    for i in range(250):
        own = list(words)
        for at in rng.choice(150, int(rng.integers(1, 5)), replace=False):
            own[at] = f"n{i}.{at}"
        rows.append((i, " ".join(own)))
    assert groups(spark, rows) == plain_groups(rows)


def test_shingles_are_counted_over_all_rows(spark):
    docs = spark.range(60_000).select(F.col("id").alias("doc_id"), F.lit("one two three four five").alias("text"))
    hashes, counts = simhash.common_shingles(docs, 5)
    assert len(hashes) == 1 and counts.tolist() == [60_000]
