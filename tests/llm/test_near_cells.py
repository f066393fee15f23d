"""The cells of the near stage against all pairs of texts under a key."""

import random

import numpy as np
import pytest

from rulelattice.llm import shingle_join
from tests.llm.test_advice_r01 import jaccard_groups


@pytest.mark.parametrize("block", [3, 256])
def test_cells_hold_every_open_pair_once(spark, monkeypatch, block):
    monkeypatch.setattr(shingle_join, "BLOCK", block)
    rng = random.Random(block)
    # Key 0 has one component only, key 1 a large one and others, key 2 only texts alone.
    owns = {0: [5] * 6, 1: [7] * 11 + [70 + i for i in range(9)], 2: list(range(200, 209))}
    rows, th = [], 0
    for key, own in owns.items():
        for o in own:
            rows.append((key, th, *[rng.getrandbits(60) for _ in range(shingle_join.LANES)], 100, 0, o))
            th += 1
    df = spark.createDataFrame(rows, ", ".join(f"{c} long" for c in shingle_join.KEYED))
    cells = {}
    for r in shingle_join._cells(df).collect():
        cells.setdefault((r["key"], r["i"], r["j"]), []).append((r["block"], r["th"], r["own"]))
    got = []
    for (key, i, j), held in cells.items():
        left, right = ([h for h in held if h[0] == x] for x in (i, j))
        got += [(key, *sorted((a[1], b[1]))) for x, a in enumerate(left) for y, b in enumerate(right) if a[2] != b[2] and (i != j or x < y)]
    want = {(a[0], a[1], b[1]) for a in rows for b in rows if a[0] == b[0] and a[1] < b[1] and a[-1] != b[-1]}
    assert len(got) == len(set(got)) and set(got) == want
    assert not any(key == 0 for key, _, _ in cells)


def test_group_of_texts_that_are_nearly_alike_enough(spark, monkeypatch):
    monkeypatch.setattr(shingle_join, "BLOCK", 16)
    monkeypatch.setattr(shingle_join, "EARLY", 1)
    rng = random.Random(5)
    words = [f"w{i}" for i in range(3000)]
    base = rng.choices(words, k=150)

    def varied(text, times):
        text = list(text)
        for _ in range(times):
            text[rng.randrange(len(text))] = rng.choice(words)
        return text

    # Two of a group differ in about eight words in the middle, so their similarity lies about 0.6; some have a closer one.
    group = [varied(base, 4) for _ in range(90)]
    group += [varied(t, 1) for t in group[:30]]
    rows = [(i, " ".join(t)) for i, t in enumerate(group + [rng.choices(words, k=150) for _ in range(60)])]
    rows.append((1000, rows[0][1] + " end"))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = jaccard_groups(rows)
    assert 60 < len(want) < len(rows)
    assert {r["doc_id"] for r in shingle_join.one_of_each(docs).collect()} == want


def test_keys_of_a_fingerprint_are_its_drawn_bits():
    drawn = shingle_join.drawn_bits(3, 5)
    prints = np.random.default_rng(1).integers(-(1 << 62), 1 << 62, (4, shingle_join.LANES))
    for row, keys in zip(prints.tolist(), shingle_join.table_keys(prints, drawn).tolist(), strict=True):
        bit = lambda x: row[x // 64] >> (x % 64) & 1  # noqa: B023, E731
        assert keys == [t << 5 | sum(bit(x) << k for k, x in enumerate(bits)) for t, bits in enumerate(drawn.tolist())]
