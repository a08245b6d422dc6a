"""The parts that the methods are named for: positions, merges, automata, mixtures, and spans that only a model finds."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from seqstat.llm import exact_dedup, language_id, mixing, pii, queries, secret_scan, simhash, toxicity

SF = "/root/testdata/sf0.001"


def test_positions_invert_the_integral(spark):
    """The schedules summed in small steps reach a copy's share of the target at its position."""
    plan = mixing.Curriculum()
    grid = np.linspace(0, 1, 200_001)
    totals = []
    for schedule in plan.schedules:
        height = np.interp(grid, *zip(*schedule, strict=True))
        area = np.concatenate([[0], np.cumsum((height[1:] + height[:-1]) / 2 * np.diff(grid))])
        totals.append(area / area[-1])
    rows = spark.read.parquet(f"{SF}/documents.parquet")
    names = sorted({r["source"] for r in rows.select("source").collect() if r["source"] is not None})
    for r in mixing.assign(rows).collect():
        budget = round(r["target"])
        kind = (names.index(r["source"]) if r["source"] is not None else len(names)) % 3
        starts = {round(float(np.interp(c["position"], grid, totals[kind])) * budget) for c in r["copies"]}
        assert len(starts) == len(r["copies"])
        first = min(starts, default=0)
        assert all(abs((s - first) % r["source_size"]) <= 2 or abs((s - first) % r["source_size"] - r["source_size"]) <= 2 for s in starts)


def test_runs_are_merged_sorted(spark, capsys):
    leaf = spark.createDataFrame([(0, b"a", 1, 1, 5), (1, b"a", 1, 1, 3), (1, b"b", 2, 1, None)], "run int, digest binary, check long, octets int, doc_id long")
    merged = exact_dedup.merge_runs(leaf)
    merged.explain()
    plan = capsys.readouterr().out
    assert "SortAggregate" in plan and "HashAggregate" not in plan
    assert {(bytes(r["digest"]), r["keep_id"], r["group_size"]) for r in merged.collect()} == {(b"a", 3, 2), (b"b", None, 1)}


def last_row(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (x != y)))
        row = new
    return row


@pytest.mark.parametrize("edits", [1, 2])
def test_automaton_against_plain_distances(edits):
    rng = random.Random(1)
    for _ in range(15):
        terms = {"".join(rng.choice("abcd") for _ in range(rng.randint(5, 9))) + "*" * (rng.random() < 0.4): rng.random() + 0.1 for _ in range(20)}
        lexicon = toxicity.Lexicon(terms, edits=edits)
        for _ in range(100):
            word = list(rng.choice(list(terms)).rstrip("*"))
            for _ in range(rng.randint(0, edits + 1)):
                at = rng.randrange(len(word) + 1)
                word[at : at + rng.randint(0, 1)] = rng.choice(["", "a", "b", "c", "d"])
            word = "".join(word) + "dcba"[: rng.randint(0, 4) * (rng.random() < 0.3)]
            want = 0.0
            for t, weight in terms.items():
                bare = t.rstrip("*")
                if len(bare) >= 5 + (t != bare) and len(word) >= 5 - edits:
                    row = last_row(bare, word)
                    want = max(want, weight if row[-1] <= edits or t != bare and min(row) <= edits else 0.0)
            assert lexicon.fuzzy(word) == pytest.approx(want)


def test_misspelled_and_quoted_terms():
    hits = toxicity.Hits(toxicity.Lexicon({"grumble": 3.0, "snarki*": 2.0}))
    plain, misspelled, quoted = (toxicity.features(t, hits) for t in ("you grumble at us", "you grumbel gruble at us", 'they said "you grumble" to us'))
    assert plain[1] > 0 and plain[2] == 0 and plain[3] == 0
    assert misspelled[1] == 0 and misspelled[2] > 0
    assert quoted[1] == plain[1] and quoted[3] > 0
    assert hits["snarkily"] == 2.0 and hits["snrakliy"] == 0 and hits["snaarkily"] == -2.0 and hits["gentle"] == 0


def test_mixture_against_plain_em():
    rng = np.random.default_rng(2)
    logs = rng.normal(-8, 3, (30, 4)).astype(np.float64)
    starts = np.array([0, 12])
    share, fit = language_id.mixtures(logs, starts, np.ones((2, 4)), 12)
    for d, (a, b) in enumerate(((0, 12), (12, 30))):
        p = [0.25] * 4
        for _ in range(12):
            parts = []
            for row in logs[a:b]:
                joint = [p[k] * np.exp(row[k]) for k in range(4)]
                parts.append([x / sum(joint) for x in joint])
            p = [sum(x[k] for x in parts) / (b - a) for k in range(4)]
        assert share[d] == pytest.approx(p)
        assert fit[d] == pytest.approx(sum(np.log(sum(p[k] * np.exp(row[k]) for k in range(4))) for row in logs[a:b]))


@pytest.mark.parametrize("languages", [1, 2, 3, 4])
def test_texts_in_several_languages(languages):
    rng = random.Random(3)
    syllables = [["ka", "ro", "mi"], ["sch", "ung", "eit"], ["tion", "ment", "eau"], ["zyk", "owo", "prz"]]
    word = lambda k: "".join(rng.choice(syllables[k]) for _ in range(3))
    models = language_id.train([(f"l{k}", " ".join(word(k) for _ in range(3000))) for k in range(4)])
    logs = models.words([word(i % languages) for i in range(120)])
    best, share, size = language_id.identify(logs, np.array([0]))
    assert size[0] == languages and best[0] < languages and share[0] == pytest.approx(1 / languages, abs=0.08)


def test_sets_grow_per_document():
    """Documents judged together get what each gets alone."""
    rng = np.random.default_rng(4)
    logs = rng.normal(-8, 3, (200, 5)).astype(np.float32)
    starts = np.array([0, 3, 50, 51, 120])
    together = language_id.identify(logs, starts)
    for d, (a, b) in enumerate(zip(starts, [*starts[1:], 200], strict=True)):
        alone = language_id.identify(logs[a:b], np.array([0]))
        assert [x[0] for x in alone] == pytest.approx([x[d] for x in together])


def test_classes_without_ids_bridge(spark):
    rng = np.random.default_rng(5)
    words = [f"w{i}" for i in range(400)]
    texts = {}
    while len(texts) < 3:
        own = list(words)
        for at in rng.choice(400, 2 * len(texts), replace=False):
            own[at] = f"x{at}"
        texts[len(texts)] = " ".join(own)
    prints = {i: simhash.majority(simhash.shingle_hashes(t.encode().split(), 3)) & (1 << 64) - 1 for i, t in texts.items()}
    classes = spark.createDataFrame([(1, texts[0]), (None, texts[1]), (2, texts[2])], "doc_id long, text string")
    found = {r["doc_id"]: r["component_id"] for r in simhash.fingerprint_components(classes).collect()}
    near = lambda a, b: (prints[a] ^ prints[b]).bit_count() <= 2
    joined = near(0, 2) or near(0, 1) and near(1, 2)
    assert found[2] == (1 if joined else 2)


@pytest.fixture(scope="module")
def tagger(spark):
    texts = [r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").select("text").orderBy("doc_id").collect()]
    return pii.trained([t for t in texts if pii.DIGITS_OR_AT.search(t)])


def found_in(model, text):
    return pii.model_spans(text, next(pii.tag_texts(model, [text], pii.Windows())))


def test_windows_left_out_change_nothing(spark, tagger):
    texts = [r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").select("text").collect()] + ["", "7", "@" * 200, "a" * 31 + "1" + "b" * 500]
    for text, lazy, full in zip(texts, pii.tag_texts(tagger, texts, pii.Windows()), pii.tag_texts(tagger, texts, pii.Windows(), lazy=False), strict=True):
        assert pii.model_spans(text, lazy) == pii.model_spans(text, full)
        digits = np.flatnonzero((pii.classes(text) == 3) | (pii.classes(text) == 5))
        assert (lazy[digits] == full[digits]).all()


def test_spans_across_window_edges(tagger):
    """Two spans at every place of the grid: nine tenths are found, and whole."""
    hits = []
    for gap in range(64):
        text = "word " * 6 + "x" * gap + " call (743) 555-3824 or write to john.smith@localhost today"
        kinds = {text[a:b]: k for a, b, k in found_in(tagger, text)}
        assert set(kinds) <= {"(743) 555-3824", "john.smith@localhost"}
        hits += [kinds.get("(743) 555-3824") == "lstm_phone", kinds.get("john.smith@localhost") == "lstm_email"]
    assert sum(hits) >= 0.9 * len(hits)


def test_long_addresses_are_whole(tagger):
    name = "a.very.long.name.that.goes.on.and.on.for.more.than.a.window.of.characters.indeed"
    text = f"write to {name}@localhost today"
    for a, b, _ in found_in(tagger, text):
        assert text[a:b] == f"{name}@localhost"


def test_numbers_that_fail_the_check_add_nothing(tagger):
    rng = np.random.default_rng(6)
    for i in range(200):
        number = pii.luhn_number(rng, 16)
        wrong = number[:-1] + str((int(number[-1]) + 1 + i % 9) % 10)
        for by in ("", " ", "-", "."):
            assert not [s for s in found_in(tagger, f"the number {pii.grouped(wrong, by)} was given") if s[2] == "lstm_card"]
    for text in ("my number is 123-45-6789.", "on 2021-03-04 at 10:45:12", "ISBN 978-3-16-148410-0", "@someone said"):
        assert found_in(tagger, text) == []


@pytest.fixture(scope="module")
def planted_tables(spark, tmp_path_factory):
    """The documents with spans in them that no pattern finds."""
    folder, rng = str(tmp_path_factory.mktemp("planted")), np.random.default_rng(7)
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    keys = secret_scan.generated(80, seed=123)
    keys = [k for k in keys if not secret_scan.base_spans(k)][:50]
    forms = [f for f in (pii.written(rng) for _ in range(200)) if not pii.base_spans(f[0])][:100]
    rows = [(10_000 + i, f"this was sent over {k} and so it went on", "en", "planted", 0) for i, k in enumerate(keys)]
    rows += [(20_000 + i, f"this was sent over {f} and so it went on", "en", "planted", 0) for i, (f, _) in enumerate(forms)]
    docs.unionByName(spark.createDataFrame(rows, docs.schema)).write.parquet(f"{folder}/documents.parquet")
    return folder, keys, forms


def test_keys_found_through_the_query(spark, planted_tables):
    folder, keys, _ = planted_tables
    rows = queries.op4_markov_secrets(spark, folder).where(F.col("doc_id").between(10_000, 19_999)).collect()
    assert len(rows) == len(keys) >= 30
    assert sum(f"random:19:{19 + len(keys[r['doc_id'] - 10_000])}" in r["spans"] for r in rows) >= 0.9 * len(keys)


def test_forms_found_through_the_query(spark, planted_tables):
    folder, _, forms = planted_tables
    rows = queries.op10_bilstm_pii(spark, folder).where("doc_id >= 20000").collect()
    whole = [f"lstm_{forms[r['doc_id'] - 20_000][1]}:19:{19 + len(forms[r['doc_id'] - 20_000][0])}" in r["spans"] for r in rows]
    assert len(rows) == len(forms) >= 60 and sum(whole) >= 0.9 * len(forms)
