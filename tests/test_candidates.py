"""Generated candidates are made where the windows of their overlap are."""

import random
from collections import Counter
from functools import partial

import pyarrow as pa
import pytest

from seqstat.functions import text
from seqstat.operators import candidate_kernel as kernel
from seqstat.operators import levelwise_scan as scan
from seqstat.operators.encode import prepare
from seqstat.operators.suffix import suffix_scan


@pytest.mark.parametrize("block", [1, 5, 1 << 20])
@pytest.mark.parametrize("size", [1, 4, 1000])
def test_kernel(monkeypatch, block, size):
    """Every candidate is made once, whatever the blocks and batches; windows that are none aren't counted."""
    monkeypatch.setattr(kernel, "BLOCK", block)
    rng = random.Random(4)
    level = {(rng.randrange(1, 6), rng.randrange(1, 6)) for _ in range(14)}
    seen = Counter(tuple(rng.randrange(1, 7) for _ in range(3)) for _ in range(900))
    rows = [(b, a % 2, kernel.LEFT, a << 32) for a, b in level] + [(a, salt, kernel.RIGHT, b) for a, b in level for salt in (0, 1)]
    rows = sorted(rows + [(o, a % 2, kernel.WINDOW, a << 32 | z) for a, o, z in seen.elements()])
    columns = [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.int32(), pa.int64()), strict=True)]
    batches = pa.Table.from_arrays(columns, ["o0", "salt", "kind", "word"]).to_batches(max_chunksize=size)
    made = [tuple(g) for b in kernel.made(iter(batches), ["o0"]) for g in b.column("ids").to_pylist()]
    want = {(a, b, d) for a, b in level for c, d in level if b == c}
    assert len(made) == len(want) and set(made) == want
    found = [(tuple(g), n) for b in kernel.counted(iter(batches), ["o0"], 6) for g, n in zip(b.column("ids").to_pylist(), b.column("cf").to_pylist(), strict=True)]
    assert len(found) == len(dict(found)) and dict(found) == {g: n for g, n in seen.items() if g in want and n >= 6}


@pytest.mark.parametrize("grams", [0, 1000])
def test_candidates_cross_no_exchange(spark, monkeypatch, capsys, grams):
    """Windows and grams are dealt by their overlap in one exchange, and no row is made for a candidate; levels that are sent or not, in turns or not."""
    rng = random.Random(6)
    p = prepare(text.literal(spark, *[" ".join(f"w{rng.choice((0, 0, 0, 1, 2, 3, 4))}" for _ in range(rng.randrange(1, 40))) for _ in range(25)]), 3)
    want = {tuple(r["ids"]): r["cf"] for r in suffix_scan(p, 3, 4).collect()}
    monkeypatch.setattr(scan, "BROADCAST_GRAMS", grams)
    monkeypatch.setattr(scan, "generated", None)
    staged, stage = [], scan.stage
    monkeypatch.setattr(scan, "stage", lambda df, name, **kw: staged.append((name, df)) or stage(df, name, **kw))
    for bytes_ in (1 << 30, 4000):
        monkeypatch.setattr(scan, "counted_generated", partial(scan.counted_generated, turn_bytes=bytes_))
        assert {tuple(r["ids"]): r["cf"] for r in scan.levelwise_scan(p, 3, 4, candidates="generated").collect()} == want
    capsys.readouterr()
    scan.overlapping(stage(suffix_scan(p, 3, 2).where("size(ids) = 2"), "level"), 3, None, p.runs)[0].explain()
    assert capsys.readouterr().out.count("Exchange hashpartitioning") == 1
    assert sum(name == "turn" for name, _ in staged) > 4
