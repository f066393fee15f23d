"""Byte-level BPE encoding and decoding by corpus-level merge replay.

The distinct pre-tokens of a batch of texts are laid out as one array of byte symbols. An inverted
index leads from each mergeable pair's rank to the positions where the pair stands; ranks are taken
from the lowest up, all their positions are merged at once, and only the pairs of the neighbours that a
merge touched are looked up again and entered into the index. Texts are then read off through their
pre-tokens. Ranks are those of merged byte strings, as in the rank files of public tokenizers, so a
merge can make a pair of a lower rank; the index hands that out next. Where such a pair appears in a
pre-token in which the rank just replayed stood several times, the pre-token is merged alone, pair by
pair, because the order of its merges matters.

Edge cases: a null text is empty and has no tokens; repeated rows are encoded each; pre-tokens of any
length are encoded whole; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame

#: Characters of text whose pre-tokens are replayed together.
BATCH_CHARS = 12_000_000
NONE = np.int64(1 << 40)


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class Replay:
    """Merges of one vocabulary."""

    def __init__(self, ranks: dict[bytes, int], pattern: str) -> None:
        self.ranks, self.find = ranks, regex.compile(pattern).findall
        self.bytes_of = {i: t for t, i in ranks.items()}
        self.byte_id = np.array([ranks[bytes([b])] for b in range(256)], dtype=np.int64)
        pairs = {}
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left, right = ranks.get(token[:cut]), ranks.get(token[cut:])
                if left is not None and right is not None:
                    pairs[left << 20 | right] = rank
        self.pair_keys = np.array(sorted(pairs), dtype=np.int64)
        self.pair_ranks = np.array([pairs[k] for k in sorted(pairs)], dtype=np.int64)

    def rank_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left << 20 | right
        at = np.minimum(np.searchsorted(self.pair_keys, key), len(self.pair_keys) - 1)
        return np.where(self.pair_keys[at] == key, self.pair_ranks[at], NONE)

    def alone(self, word: bytes) -> list[int]:
        """One pre-token, always merging the leftmost pair of the lowest rank; pairs wait in a heap."""
        names: list[bytes | None] = [bytes([b]) for b in word]
        after, before = list(range(1, len(word) + 1)), list(range(-1, len(word) - 1))
        heap = [(r, i, 2) for i in range(len(word) - 1) if (r := self.ranks.get(word[i : i + 2])) is not None]
        heapq.heapify(heap)

        def enter(i: int) -> None:
            if i >= 0 and after[i] < len(word):
                pair = names[i] + names[after[i]]
                if (r := self.ranks.get(pair)) is not None:
                    heapq.heappush(heap, (r, i, len(pair)))

        while heap:
            rank, i, size = heapq.heappop(heap)
            j = after[i]
            # A pair that has changed since was entered anew, with another rank or length.
            if names[i] is None or j >= len(word) or len(names[i]) + len(names[j]) != size or self.ranks[names[i] + names[j]] != rank:
                continue
            names[i], names[j] = names[i] + names[j], None
            after[i] = after[j]
            if after[j] < len(word):
                before[after[j]] = i
            enter(i)
            enter(before[i])
        return [self.ranks[n] for n in names if n is not None]

    def encode_words(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Token ids of all words one after another, and the number of each word's tokens."""
        if not words:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        token = self.byte_id[np.frombuffer(b"".join(words), np.uint8)]
        total = len(token)
        word_at = np.repeat(np.arange(len(words)), sizes)
        after, before = np.arange(1, total + 1), np.arange(-1, total - 1)
        ends = np.cumsum(sizes) - 1
        after[ends[sizes > 0]] = total
        before[(np.cumsum(sizes) - sizes)[sizes > 0]] = -1
        rank = np.full(total + 1, NONE)  # of the pair that starts here; the last cell stands for no position
        inner = np.flatnonzero(after < total)
        rank[inner] = self.rank_of(token[inner], token[after[inner]])
        alive = np.ones(total, bool)
        index: dict[int, list[np.ndarray]] = {}
        heap: list[int] = []

        def enter(places: np.ndarray) -> None:
            places = places[rank[places] < NONE]
            if not len(places):
                return
            order = np.argsort(rank[places], kind="stable")
            places = places[order]
            held = rank[places]
            cuts = np.flatnonzero(held[1:] != held[:-1]) + 1
            for r, part in zip(held[np.r_[0, cuts]].tolist(), np.split(places, cuts), strict=True):
                if r in index:
                    index[r].append(part)
                else:
                    index[r] = [part]
                    heapq.heappush(heap, r)

        enter(np.arange(total))
        odd: set[int] = set()
        while heap:
            r = heapq.heappop(heap)
            parts = index.pop(r)
            places = np.unique(parts[0] if len(parts) == 1 else np.concatenate(parts))
            places = places[alive[places] & (rank[places] == r)]
            if not len(places):
                continue
            # Where a pair overlaps the next one (as in "aaa"), every second of the run merges.
            linked = np.r_[False, after[places[:-1]] == places[1:]]
            if linked.any():
                runs = np.cumsum(~linked) - 1
                first = np.flatnonzero(~linked)
                places = places[(np.arange(len(places)) - first[runs]) % 2 == 0]
            right = after[places]
            own = word_at[places]
            if (own[1:] == own[:-1]).any():
                # A pre-token in which one of these merges would at once open a pair of a lower rank.
                beyond, left, merged = after[right], before[places], np.full(len(places), r)
                opens = (beyond < total) & (self.rank_of(merged, token[np.minimum(beyond, total - 1)]) < r)
                opens |= (left >= 0) & (self.rank_of(token[np.maximum(left, 0)], merged) < r)
                beside = np.r_[beyond[:-1] == places[1:], False]
                opens |= beside & (self.rank_of(merged, merged) < r)
                if opens.any():
                    held, times = np.unique(own, return_counts=True)
                    odd.update(np.intersect1d(held[times > 1], own[opens]).tolist())
            token[places] = r
            alive[right] = False
            rank[right] = NONE
            beyond = after[right]
            after[places] = beyond
            inside = beyond < total
            before[beyond[inside]] = places[inside]
            rank[places] = NONE
            rank[places[inside]] = self.rank_of(token[places[inside]], token[beyond[inside]])
            left = before[places]
            left = left[left >= 0]
            rank[left] = self.rank_of(token[left], token[after[left]])
            touched = np.unique(np.r_[places, left])
            enter(touched)
        flat, counts = token[alive], np.bincount(word_at[alive], minlength=len(words))
        if odd:
            lists = np.split(flat, np.cumsum(counts)[:-1])
            for w in odd:
                lists[w] = np.array(self.alone(words[w]), np.int64)
            flat, counts = np.concatenate(lists), np.fromiter(map(len, lists), np.int64, len(lists))
        return flat, counts

    def encode(self, texts: list[str]) -> list[list[int]]:
        found = [self.find(t) for t in texts]
        words = list(dict.fromkeys(w for f in found for w in f))
        flat, counts = self.encode_words([w.encode("utf-8", "surrogatepass") for w in words])
        ids = dict(zip(words, (x.tolist() for x in np.split(flat, np.cumsum(counts)[:-1])), strict=True)) if words else {}
        return [[i for w in f for i in ids[w]] for f in found]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))

    def digests(self, texts: list[str]) -> Iterator[tuple[int, str, str]]:
        """Number of tokens, SHA-256 of the ids joined by commas, SHA-256 of the decoded bytes, of each text."""
        numbers = _Numbers()
        found = [np.fromiter(map(numbers.__getitem__, self.find(t)), np.int32) for t in texts]
        flat, counts = self.encode_words([w.encode("utf-8", "surrogatepass") for w in numbers])
        names, pieces = list(map(str, flat.tolist())), list(map(self.bytes_of.__getitem__, flat.tolist()))
        ends = np.cumsum(counts).tolist()
        ids = [",".join(names[e - n : e]) for e, n in zip(ends, counts.tolist(), strict=True)]
        decoded = [b"".join(pieces[e - n : e]) for e, n in zip(ends, counts.tolist(), strict=True)]
        del names, pieces
        for f in found:
            at = f.tolist()
            joined = ",".join(map(ids.__getitem__, at))
            yield int(counts[f].sum()), hashlib.sha256(joined.encode()).hexdigest(), hashlib.sha256(b"".join(map(decoded.__getitem__, at))).hexdigest()


class _Numbers(dict):
    """Numbers new keys in the order in which they are met."""

    def __missing__(self, key: str) -> int:
        self[key] = n = len(self)
        return n


@lru_cache(maxsize=2)
def replay_of(path: str, pattern: str) -> Replay:
    return Replay(read_ranks(path), pattern)


def batched(texts: list[str], limit: int = BATCH_CHARS) -> Iterator[list[str]]:
    """Runs of texts with about so many characters; a longer text is a run of its own."""
    run, size = [], 0
    for t in texts:
        if run and size + len(t) > limit:
            yield run
            run, size = [], 0
        run.append(t)
        size += len(t)
    if run:
        yield run


def encode_column(docs: DataFrame, rank_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each document's id with its token ids."""
    kind = dict(docs.dtypes)[id_col]

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        replay = replay_of(rank_path, pattern)
        for pdf in batches:
            ids = [x for run in batched([t or "" for t in pdf[text_col]]) for x in replay.encode(run)]
            yield pd.DataFrame({id_col: pdf[id_col], "token_ids": ids})

    return docs.select(id_col, text_col).mapInPandas(rows, f"{id_col} {kind}, token_ids array<int>")


def decode_column(tokens: DataFrame, rank_path: str, pattern: str, id_col: str = "doc_id") -> DataFrame:
    """Each document's id with its text; bytes that are not UTF-8 are replaced."""
    kind = dict(tokens.dtypes)[id_col]

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        replay = replay_of(rank_path, pattern)
        for pdf in batches:
            yield pd.DataFrame({id_col: pdf[id_col], "text": [replay.decode(list(x)).decode("utf-8", "replace") for x in pdf["token_ids"]]})

    return tokens.select(id_col, "token_ids").mapInPandas(rows, f"{id_col} {kind}, text string")


def round_trip_digests(docs: DataFrame, rank_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: number of tokens, digest of its ids, digest of the bytes decoded from them."""
    import pyarrow as pa

    kind = dict(docs.dtypes)[id_col]

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        replay = replay_of(rank_path, pattern)

        def made(ids: list, texts: list[str]) -> pa.RecordBatch:
            out = [x for run in batched(texts) for x in replay.digests(run)]
            return pa.RecordBatch.from_arrays([pa.array(ids, id_type), pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.string()), pa.array([x[2] for x in out], pa.string())], [id_col, "n_tokens", "ids_sha256", "decoded_sha256"])

        ids, texts, size, id_type = [], [], 0, None
        for batch in batches:
            id_type = batch.schema.field(0).type
            for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids.append(i)
                texts.append(t or "")
                size += len(texts[-1])
                if size >= BATCH_CHARS:
                    yield made(ids, texts)
                    ids, texts, size = [], [], 0
        if ids:
            yield made(ids, texts)

    return docs.select(id_col, text_col).mapInArrow(rows, f"{id_col} {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
