"""Substring deduplication with longest-previous-factor arrays over a partitioned suffix array.

A byte is removed when a string of ``length`` bytes that covers it also starts in a document with a
smaller id. Suffixes that share so many first bytes must meet in one place, so every suffix is sent
where the smallest hashed ``GRAM``-gram of its first ``length`` bytes says, a key that neighbouring
suffixes mostly share. The work goes in four steps, of which the texts take part in three through one
and the same exchange:

1. each group of documents lists its distinct keys; keys found in one group only are dropped;
2. each group sends, for the keys that are left, the stretch of text that its suffixes span; a stretch
   that a smaller document of the group holds too is settled at once, so a passage that many documents
   share is sent once a group;
3. each shard of keys sorts its suffixes, takes the common prefixes of neighbours, and finds with the
   previous and the next smaller document in suffix order the longest earlier match of each;
4. the ranges so covered go back to the groups, which cut them out.

Edge cases: a null text is empty; a null id ranks before all others; documents with the same id are no
copies of each other; matches never cross documents; texts shorter than ``length`` stay as they are;
an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LENGTH = 50
GRAM = 16
#: Bytes of text of a group of documents, and of text that is hashed at once.
GROUP_BYTES = 8_000_000
CHUNK_BYTES = 1 << 18
#: Shards of keys to a group of documents.
SHARDS_A_GROUP = 4
NULL_ID = -(1 << 63)
_M1, _M2, _M3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


# Suffix order and earlier matches --------------------------------------------------------------


def suffix_order(windows: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """Order of equally long suffixes (rows of bytes), equal ones by owner."""
    n, width = windows.shape
    # Rows with their owner behind them, as unsigned big-endian, are sorted once as strings of bytes.
    rows = np.zeros((n, width + 8), np.uint8)
    rows[:, :width] = windows
    rows[:, width:] = (owner.astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63)).astype(">u8").view(np.uint8).reshape(n, 8)
    return np.argsort(rows.view(f"S{width + 8}").ravel(), kind="stable")


def common_prefixes(windows: np.ndarray) -> np.ndarray:
    """Common prefix of each row with the one before; zero for the first."""
    out = np.zeros(len(windows), np.int64)
    if len(windows) > 1:
        differs = windows[1:] != windows[:-1]
        out[1:] = np.where(differs.any(axis=1), differs.argmax(axis=1), windows.shape[1])
    return out


def previous_smaller(owner: np.ndarray, prefix: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Place of the last earlier suffix with a smaller owner (-1: none), and the prefix shared with it."""
    n = len(owner)
    at, low = np.arange(n) - 1, prefix.copy()
    open_ = np.arange(n)
    while len(open_):
        j = at[open_]
        open_ = open_[(j >= 0) & (owner[np.maximum(j, 0)] >= owner[open_])]
        j = at[open_]
        low[open_], at[open_] = np.minimum(low[open_], low[j]), at[j]
    low[at < 0] = 0
    return at, low


def longest_previous_factor(owner: np.ndarray, prefix: np.ndarray) -> np.ndarray:
    """For suffixes in order: the longest prefix that one of a smaller owner shares, before or after it."""
    back = previous_smaller(owner, prefix)[1]
    ahead = np.r_[prefix[1:], 0][::-1] if len(prefix) else prefix
    return np.maximum(back, previous_smaller(owner[::-1], ahead.copy())[1][::-1])


# Keys of suffixes --------------------------------------------------------------------------------


def gram_hashes(data: np.ndarray, k: int) -> np.ndarray:
    """Hash of every k-gram, put together from those of powers of two."""
    h = (data.astype(np.uint64) + np.uint64(1)) * _M1
    h ^= h >> np.uint64(29)
    n = 1
    while n < k:
        step = min(n, k - n)
        h = h[:-step] * _M2 + h[step:]
        h ^= h >> np.uint64(31)
        h *= _M3
        n += step
    return h


def sliding_least(h: np.ndarray, width: int) -> np.ndarray:
    n = 1
    while n < width:
        step = min(n, width - n)
        h = np.minimum(h[:-step], h[step:])
        n += step
    return h


def gram_of(length: int) -> int:
    return max(1, min(GRAM, length // 2))


def stretches(texts: list[bytes], length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of suffixes of one document that share a key: key, document, first suffix, their number."""
    parts: list[tuple[np.ndarray, ...]] = []
    k, at = gram_of(length), 0
    while at < len(texts):
        end, size = at, 0
        while end < len(texts) and (end == at or size + len(texts[end]) <= CHUNK_BYTES):
            size += len(texts[end])
            end += 1
        sizes = np.fromiter(map(len, texts[at:end]), np.int64, end - at)
        data = np.frombuffer(b"".join(texts[at:end]), np.uint8)
        if len(data) >= length:
            keys = sliding_least(gram_hashes(data, k), length - k + 1)
            ends = np.cumsum(sizes)
            owner = np.repeat(np.arange(end - at), sizes)[: len(keys)]
            whole = np.flatnonzero(np.arange(length, len(data) + 1) <= ends[owner])
            if len(whole):
                key, own = keys[whole], owner[whole]
                new = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]) | (own[1:] != own[:-1])])
                parts.append((key[new], own[new] + at, whole[new] - (ends - sizes)[own[new]], np.diff(np.r_[new, len(key)])))
        at = end
    if not parts:
        return np.empty(0, np.uint64), *[np.empty(0, np.int64)] * 3
    return tuple(np.concatenate(c) for c in zip(*parts, strict=True))


# Steps -----------------------------------------------------------------------------------------------


def _sorted_rows(table: pa.Table) -> tuple[list[int | None], np.ndarray, list[bytes]]:
    """Ids, ids as ranks, texts; in an order that does not depend on the exchange."""
    ids, texts = table.column("doc_id").to_pylist(), [t or b"" for t in table.column("text").to_pylist()]
    order = sorted(range(len(ids)), key=lambda i: (ids[i] is not None, ids[i] or 0, texts[i]))
    ids = [ids[i] for i in order]
    return ids, np.array([NULL_ID if i is None else i for i in ids], np.int64), [texts[i] for i in order]


def _by(place: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """Each value with the places where it stands."""
    if len(place):
        order = np.argsort(place, kind="stable")
        cuts = np.flatnonzero(np.diff(place[order])) + 1
        for part in np.split(order, cuts):
            yield int(place[part[0]]), part


def _keys_of(length: int, shards: int):
    def run(key: tuple, table: pa.Table) -> pa.Table:
        _, _, texts = _sorted_rows(table)
        keys = np.unique(stretches(texts, length)[0])
        made = [(s, keys[at].tobytes()) for s, at in _by(keys % np.uint64(shards))]
        return pa.table({"shard": pa.array([m[0] for m in made], pa.int32()), "p": pa.array([key[0].as_py()] * len(made), pa.int32()), "keys": pa.array([m[1] for m in made], pa.binary())})
    return run


def _shared_keys(table: pa.Table) -> pa.Table:
    """Keys that several groups hold, for each group."""
    groups = table.column("p").to_pylist()
    lists = [np.frombuffer(k, np.uint64) for k in table.column("keys").to_pylist()]
    keys = np.concatenate(lists)
    group = np.repeat(np.array(groups, np.int64), [len(x) for x in lists])
    order = np.argsort(keys, kind="stable")
    same = keys[order][1:] == keys[order][:-1]
    shared = order[np.r_[False, same] | np.r_[same, False]]
    made = [(g, keys[shared[at]].tobytes()) for g, at in _by(group[shared])]
    return pa.table({"p": pa.array([m[0] for m in made], pa.int32()), "keys": pa.array([m[1] for m in made], pa.binary())})


def _stretches_of(length: int, shards: int):
    def run(key: tuple, docs: pa.Table, shared: pa.Table) -> pa.Table:
        _, rank, texts = _sorted_rows(docs)
        keys, doc, first, count = stretches(texts, length)
        asked = np.sort(np.concatenate([np.empty(0, np.uint64), *[np.frombuffer(k, np.uint64) for k in shared.column("keys").to_pylist()]]))
        hit = np.zeros(len(keys), bool)
        if len(asked):
            hit = asked[np.minimum(np.searchsorted(asked, keys), len(asked) - 1)] == keys
        order = np.argsort(keys, kind="stable")
        k, r = keys[order], rank[doc[order]]
        if len(k):
            run_of = np.cumsum(np.r_[True, k[1:] != k[:-1]]) - 1
            several = np.zeros(run_of[-1] + 1, bool)
            np.logical_or.at(several, run_of, r != r[np.r_[True, k[1:] != k[:-1]]][run_of])
            hit[order] |= several[run_of]
        send, settled, seen = [], [], {}
        bodies = []
        for i in np.flatnonzero(hit).tolist():  # documents come by rank, so the first holder has the smallest id
            d, s, n = int(doc[i]), int(first[i]), int(count[i])
            body = texts[d][s : s + n + length - 1]
            holder = seen.setdefault(body, rank[d])
            if holder < rank[d]:
                settled.append((d, s, s + n + length - 1))
            else:
                send.append(i)
                bodies.append(body)
        sent = np.array(send, np.int64)
        p, made = key[0].as_py(), []
        for shard, at in _by(keys[sent] % np.uint64(shards)):
            own = sent[at]
            meta = np.stack([rank[doc[own]], doc[own], first[own], count[own]], axis=1).astype(np.int64)
            made.append((shard, meta.tobytes(), b"".join(bodies[j] for j in at.tolist()), b""))
        if settled:
            made.append((p % shards, b"", b"", np.array(settled, np.int64).tobytes()))
        return pa.table({"shard": pa.array([m[0] for m in made], pa.int32()), "p": pa.array([p] * len(made), pa.int32()), "meta": pa.array([m[1] for m in made], pa.binary()), "body": pa.array([m[2] for m in made], pa.binary()), "ranges": pa.array([m[3] for m in made], pa.binary())})
    return run


def covered_suffixes(owner: np.ndarray, count: np.ndarray, body: np.ndarray, length: int) -> np.ndarray:
    """Which suffixes of stretches (owner, number of suffixes; bodies one after another) have an earlier match."""
    sizes = count + length - 1
    begins = np.cumsum(sizes) - sizes
    total = int(count.sum())
    stretch = np.repeat(np.arange(len(count)), count)
    at = begins[stretch] + np.arange(total) - np.repeat(np.cumsum(count) - count, count)
    windows = np.lib.stride_tricks.sliding_window_view(body, length)[at]
    own = owner[stretch]
    order = suffix_order(windows, own)
    factor = longest_previous_factor(own[order], common_prefixes(windows[order]))
    out = np.zeros(total, bool)
    out[order] = factor >= length
    return out


def _ranges_of(length: int):
    def run(table: pa.Table) -> pa.Table:
        rows = [r for r in zip(table.column("p").to_pylist(), table.column("meta").to_pylist(), table.column("body").to_pylist(), table.column("ranges").to_pylist(), strict=True)]
        made = [(p, done) for p, _, _, done in rows if done]
        full = [r for r in rows if r[1]]
        if full:
            metas = [np.frombuffer(m, np.int64).reshape(-1, 4) for _, m, _, _ in full]
            group = np.repeat(np.array([r[0] for r in full], np.int64), [len(m) for m in metas])
            meta = np.concatenate(metas)
            count = meta[:, 3]
            hit = covered_suffixes(meta[:, 0], count, np.frombuffer(b"".join(r[2] for r in full), np.uint8), length)
            stretch = np.repeat(np.arange(len(count)), count)[hit]
            start = (meta[:, 2][np.repeat(np.arange(len(count)), count)] + np.arange(len(hit)) - np.repeat(np.cumsum(count) - count, count))[hit]
            if len(start):
                new = np.flatnonzero(np.r_[True, (stretch[1:] != stretch[:-1]) | (start[1:] != start[:-1] + 1)])
                last = np.r_[new[1:], len(start)] - 1
                spans = np.stack([meta[stretch[new], 1], start[new], start[last] + length], axis=1)
                made += [(g, spans[at].tobytes()) for g, at in _by(group[stretch[new]])]
        return pa.table({"p": pa.array([m[0] for m in made], pa.int32()), "ranges": pa.array([m[1] for m in made], pa.binary())})
    return run


def union_of(ranges: np.ndarray) -> np.ndarray:
    """Maximal runs of (start, end) rows."""
    if not len(ranges):
        return ranges.reshape(0, 2)
    ranges = ranges[np.lexsort((ranges[:, 1], ranges[:, 0]))]
    reach = np.maximum.accumulate(ranges[:, 1])
    new = np.flatnonzero(np.r_[True, ranges[1:, 0] > reach[:-1]])
    return np.stack([ranges[new, 0], np.r_[reach[new[1:] - 1], reach[-1]]], axis=1)


def _cut_out(kept_text: bool, id_type: pa.DataType):
    def run(key: tuple, docs: pa.Table, ranges: pa.Table) -> pa.Table:
        ids, _, texts = _sorted_rows(docs)
        found = np.concatenate([np.empty((0, 3), np.int64), *[np.frombuffer(r, np.int64).reshape(-1, 3) for r in ranges.column("ranges").to_pylist()]])
        own = dict(_by(found[:, 0]))
        sizes, gone, spans, kept, digests = [], [], [], [], []
        for i, text in enumerate(texts):
            runs = union_of(found[own[i]][:, 1:]).tolist() if i in own else []
            pieces, at = [], 0
            for a, b in runs:
                pieces.append(text[at:a])
                at = b
            rest = b"".join([*pieces, text[at:]])
            sizes.append(len(text))
            gone.append(len(text) - len(rest))
            spans.append([{"start": a, "end": b} for a, b in runs])
            digests.append(hashlib.sha256(rest).hexdigest())
            if kept_text:
                kept.append(rest)
        out = {"doc_id": pa.array(ids, id_type), "n_bytes": pa.array(sizes, pa.int64()), "n_removed": pa.array(gone, pa.int64()), "n_spans": pa.array(list(map(len, spans)), pa.int64()), "kept_sha256": pa.array(digests, pa.string())}
        if kept_text:
            out |= {"removed": pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), "kept": pa.array(kept, pa.binary())}
        return pa.table(out)
    return run


def remove_later_copies(docs: DataFrame, length: int = LENGTH, kept_text: bool = True, group_bytes: int = GROUP_BYTES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``n_bytes``, ``n_removed``, ``n_spans``, ``kept_sha256`` and, if asked for,
    the removed byte ranges and the kept bytes. Ids are whole numbers."""
    asked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("text"))
    total = asked.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    groups = max(1, -(-int(total) // group_bytes))
    shards = groups * SHARDS_A_GROUP
    dealt = asked.withColumn("p", F.pmod(F.xxhash64("doc_id", "text"), F.lit(groups)).cast("int"))
    keys = dealt.groupBy("p").applyInArrow(_keys_of(length, shards), "shard int, p int, keys binary")
    shared = keys.groupBy("shard").applyInArrow(_shared_keys, "p int, keys binary")
    sent = dealt.groupBy("p").cogroup(shared.groupBy("p")).applyInArrow(_stretches_of(length, shards), "shard int, p int, meta binary, body binary, ranges binary")
    ranges = sent.groupBy("shard").applyInArrow(_ranges_of(length), "p int, ranges binary")
    shape = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", removed array<struct<start:long,end:long>>, kept binary" * kept_text
    return dealt.groupBy("p").cogroup(ranges.groupBy("p")).applyInArrow(_cut_out(kept_text, pa.int64()), shape)
