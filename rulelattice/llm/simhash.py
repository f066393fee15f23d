"""SimHash near-duplicates with pivot distance tables.

A fingerprint has the bits that more than half of a text's shingle hashes have. Equal fingerprints
are brought together first, so that copies count once. Two fingerprints within ``radius`` bits agree
in three of ``radius + 3`` blocks of bits, so they meet under the key of some choice of blocks.
Under each key a table of Hamming distances to reference fingerprints (pivots) is laid out: two
fingerprints whose distances to any pivot differ by more than the radius cannot be close (triangle
inequality) and are discarded; the others are compared bit by bit. Keys with very many fingerprints
are searched by flipping bits instead of by pairs, so the work stays in proportion to them. A key
hands on only a spanning forest of its links, never all pairs.

Edge cases: a text without words (null, empty, blank) has fingerprint zero, which links like any
other; texts of fewer words than a shingle are one shingle; rows repeated with an id keep one row
each; a null id cannot name a component unless all its members' ids are null; an empty table gives
an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulelattice.llm.common import cut, set_aside
from rulelattice.llm.components import components

#: Blocks in which two close fingerprints must agree, and so the blocks beyond the radius.
AGREED = 3
PIVOTS = 24
#: A key is searched by flipping bits where it has so many times more fingerprints than there are flips.
FLIP_RATIO = 10
#: Pairs that are compared at once.
PAIRS_AT_ONCE = 2_000_000
SEED = 42


def fingerprint(text: str | None, words: int = 3) -> int:
    """Fingerprint of a text, unsigned."""
    said = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not said:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(said) <= words:
        return digest(b" ".join(said), SEED)
    whole = b" ".join(said)
    ends = np.cumsum(np.fromiter(map(len, said), np.int64, len(said)) + 1) - 1
    starts = np.r_[0, ends[: len(said) - words] + 1].tolist()
    hashes = np.array([digest(whole[s:e], SEED) for s, e in zip(starts, ends[words - 1 :].tolist(), strict=True)], np.uint64)
    return int(np.packbits(2 * bit_counts(hashes) > len(hashes), bitorder="little").view(np.uint64)[0])


def bit_counts(hashes: np.ndarray) -> np.ndarray:
    """How many of the hashes have each bit."""
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 15):
        counts += np.unpackbits(hashes[at : at + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return counts


def fingerprints(docs: DataFrame, words: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, th, fp): every row's id, a hash of its text, and its fingerprint as a signed long."""
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = np.array([fingerprint(t, words) for t in batch.column(2).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(values)], ["doc_id", "th", "fp"])

    return docs.select(F.col(id_col), F.xxhash64(text_col).alias("th"), F.col(text_col)).mapInArrow(rows, f"doc_id {dict(docs.dtypes)[id_col]}, th long, fp long")


def masks(radius: int) -> list[int]:
    """Bits of every choice of blocks that a close pair may agree in."""
    blocks = radius + AGREED
    edges = [round(i * 64 / blocks) for i in range(blocks + 1)]
    own = [((1 << (b - a)) - 1) << a for a, b in zip(edges, edges[1:], strict=False)]
    return [sum(c) for c in combinations(own, AGREED)]


def pivots(count: int = PIVOTS) -> np.ndarray:
    return np.random.default_rng(7).integers(0, 1 << 64, count, dtype=np.uint64)


def _forest(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest member of each one's component among links a-b."""
    label = np.arange(n)
    while len(a):
        low = np.minimum(label[a], label[b])
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
        open_ = label[a] != label[b]
        a, b = a[open_], b[open_]
    return label


def close_pairs(prints: np.ndarray, starts: np.ndarray, sizes: np.ndarray, radius: int, refs: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of positions within runs (start, size) whose fingerprints are close: pivots, then bits."""
    table = np.bitwise_count(prints[:, None] ^ refs[None, :]).astype(np.int8)
    rest = sizes * (sizes - 1) // 2
    at = 0
    while at < len(starts):
        take = max(1, int(np.searchsorted(np.cumsum(rest[at:]), PAIRS_AT_ONCE, "right")))
        s, n = starts[at : at + take], sizes[at : at + take]
        at += take
        firsts = np.concatenate([np.arange(x, x + k - 1) for x, k in zip(s.tolist(), n.tolist(), strict=True)])
        reach = np.concatenate([np.arange(k - 1, 0, -1) for k in n.tolist()])
        a = np.repeat(firsts, reach)
        b = a + 1 + np.arange(len(a)) - np.repeat(np.cumsum(reach) - reach, reach)
        for p in range(table.shape[1]):
            near = np.abs(table[a, p] - table[b, p]) <= radius
            a, b = a[near], b[near]
        real = np.bitwise_count(prints[a] ^ prints[b]) <= radius
        yield a[real], b[real]


def flipped_pairs(prints: np.ndarray, free: int, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Close pairs of one large run of distinct fingerprints that differ in the bits of ``free`` only."""
    order = np.argsort(prints)
    held = prints[order]
    bits = [1 << i for i in range(64) if free >> i & 1]
    for k in range(1, radius + 1):
        for some in combinations(bits, k):
            asked = held ^ np.uint64(sum(some))
            at = np.minimum(np.searchsorted(held, asked), len(held) - 1)
            hit = np.flatnonzero((held[at] == asked) & (held > asked))
            yield order[hit], order[at[hit]]


def _linked(kind: np.ndarray, key: np.ndarray, prints: np.ndarray, radius: int, choice: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links of the runs with equal (kind, key)."""
    order = np.lexsort((key, kind))
    kind, key, prints = kind[order], key[order], prints[order]
    new = np.r_[True, (kind[1:] != kind[:-1]) | (key[1:] != key[:-1])]
    starts = np.flatnonzero(new)
    sizes = np.diff(np.r_[starts, len(key)])
    pairs = []
    most = FLIP_RATIO * min(sum(comb(64 - m.bit_count(), k) for k in range(1, radius + 1)) for m in choice)
    small = (sizes > 1) & (sizes <= most)
    if small.any():
        pairs += list(close_pairs(prints, starts[small], sizes[small], radius, pivots()))
    for s, n in zip(starts[sizes > most].tolist(), sizes[sizes > most].tolist(), strict=True):
        free = ~choice[int(kind[s])] & ((1 << 64) - 1)
        pairs += [(a + s, b + s) for a, b in flipped_pairs(prints[s : s + n], free, radius)]
    if not pairs:
        return np.empty(0, np.uint64), np.empty(0, np.uint64)
    label = _forest(len(prints), np.concatenate([p[0] for p in pairs]), np.concatenate([p[1] for p in pairs]))
    moved = np.flatnonzero(label != np.arange(len(label)))
    return prints[moved], prints[label[moved]]


def links(distinct: DataFrame, radius: int = 2) -> DataFrame:
    """Links (a, b) that span the graph of close fingerprints; ``distinct`` has each long ``fp`` once."""
    choice = masks(radius)
    signed = [m - (1 << 64) if m >> 63 else m for m in choice]
    keyed = distinct.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(m).cast("long")) for m in signed])).alias("kind", "key"))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [tuple(c.to_numpy(zero_copy_only=False) for c in b.columns) for b in batches if b.num_rows]
        if held:
            fp, kind, key = (np.concatenate(c) for c in zip(*held, strict=True))
            a, b = _linked(kind, key, fp.view(np.uint64), radius, choice)
            yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

    return keyed.repartition("kind", "key").select("fp", "kind", "key").mapInArrow(rows, "a long, b long")


def _named(prints: DataFrame, radius: int) -> tuple[DataFrame, DataFrame]:
    """Fingerprints with their component's root, and roots with the row (id, text hash) that is first in it."""
    first = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), F.col("doc_id").alias("id"), F.col("th").alias("th")))
    classes = prints.groupBy("fp").agg(first.alias("least"))
    roots = components(links(classes.select("fp"), radius)).select(F.col("node").alias("fp"), "root")
    placed = classes.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    return placed.select("fp", "root"), placed.groupBy("root").agg(F.min("least").alias("least"))


def near_duplicates(docs: DataFrame, radius: int = 2, words: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id``, ``fingerprint`` (hex) and ``component_id`` (smallest id reachable)."""
    prints = cut(fingerprints(docs, words, id_col, text_col))
    placed, named = _named(prints, radius)
    classed = placed.join(named.select(F.shiftleft("root", 0).alias("_r"), F.col("least.id").alias("component_id")), F.col("root") == F.col("_r"))
    result = prints.join(classed.select(F.shiftleft("fp", 0).alias("_f"), "component_id"), F.col("fp") == F.col("_f"))
    return result.select(F.col("doc_id").alias(id_col), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, radius: int = 2, words: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each component, the one with the smallest id (a null id is last), with all its columns."""
    own, name = set_aside(docs)
    id_col, text_col = name(id_col), name(text_col)
    prints = cut(fingerprints(own, words, id_col, text_col))
    return chosen(own, prints, _named(prints, radius)[1], id_col, text_col).toDF(*docs.columns)


def chosen(own: DataFrame, rows: DataFrame, named: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The rows of ``own`` that are ``least`` in a component, one each; ``rows`` has every row's ``doc_id`` and text hash ``th``."""
    winners = named.select(F.col("least.id").alias("_id"), F.col("least.th").alias("_th"))
    repeated = rows.groupBy("doc_id", "th").agg(F.count("*").alias("_times")).where("_times > 1").select(F.col("doc_id").alias("_rid"), F.col("th").alias("_rth"), "_times")
    marked = winners.join(repeated, winners["_id"].eqNullSafe(repeated["_rid"]) & (winners["_th"] == repeated["_rth"]), "left").select("_id", "_th", F.coalesce("_times", F.lit(1)).alias("_times"))
    kept = own.join(marked, own[id_col].eqNullSafe(marked["_id"]) & (F.xxhash64(own[text_col]) == marked["_th"]))
    once = kept.where("_times = 1").select(*own.columns)
    return once.unionByName(kept.where("_times > 1").dropDuplicates(["_id", "_th"]).select(*own.columns))
