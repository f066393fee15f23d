"""Conflict-constrained best-fit packing of documents into bins of bounded size.

Documents longer than a bin are cut into pieces. Pieces are dealt to shards of bounded size by a
hash, so that a hot source or group of copies is spread over all of them, and each shard is packed
by best fit in order of falling size. A bin holds no two pieces of one source and no two members of
one duplicate cluster; it carries both as bitmaps. For a piece the search goes through the open
bins in the order of their residual room from the piece's size upwards until a compatible one is
found, which is the tightest. Sources and clusters with a large share of a shard have views of
their own on the open bins, from which bins that hold them are absent, so that the search does not
walk over them again and again.

Edge cases: pieces of a null source or null cluster conflict with none through it; documents of
size zero or null get a row without a bin; repeated rows are packed each (they conflict through
their cluster); a null id is packed like any other; an empty table gives an empty result.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections import Counter

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulelattice.llm.common import cut, shards_for
from rulelattice.llm.exact_dedup import normalised

CAPACITY = 2048
PER_SHARD = 20_000
#: A source or cluster with this share of a shard has its own view.
HEAVY = 1 / 12


class _View:
    """Open bins by residual room; ``mask`` has a bit for each room that may have bins."""

    def __init__(self, avoid: tuple[int, int]) -> None:
        self.avoid, self.mask, self.bins = avoid, 0, {}

    def add(self, room: int, at: int) -> None:
        self.mask |= 1 << room
        insort(self.bins.setdefault(room, []), at)

    def drop(self, room: int, at: int) -> None:
        held = self.bins.get(room)
        if held:
            i = bisect_left(held, at)
            if i < len(held) and held[i] == at:
                del held[i]
            if not held:
                self.mask &= ~(1 << room)


def best_fit(sizes: list[int], sources: list, clusters: list, capacity: int) -> tuple[list[int], list[int]]:
    """Bin and offset of each piece; pieces are taken in the given order."""
    source_bit = {s: i for i, s in enumerate(dict.fromkeys(s for s in sources if s is not None))}
    shared = [c for c, n in Counter(c for c in clusters if c is not None).items() if n > 1]
    cluster_bit = {c: i for i, c in enumerate(shared)}
    n, least = len(sizes), min(sizes, default=0)
    heavy_source = {s for s, k in Counter(sources).items() if s is not None and k > n * HEAVY}
    heavy_cluster = {c for c, k in Counter(clusters).items() if c in cluster_bit and k > n * HEAVY}
    keys = [(1 << source_bit[s] if s in heavy_source else 0, 1 << cluster_bit[c] if c in heavy_cluster else 0) for s, c in zip(sources, clusters, strict=True)]
    views = {k: _View(k) for k in dict.fromkeys(keys)}
    room: list[int] = []
    has_source: list[int] = []
    has_cluster: list[int] = []
    out, offsets = [], []
    for size, s, c, key in zip(sizes, sources, clusters, keys, strict=True):
        sb = 1 << source_bit[s] if s is not None else 0
        cb = 1 << cluster_bit[c] if c in cluster_bit else 0
        view, chosen = views[key], -1
        left = view.mask >> size
        at = size
        while left and chosen < 0:
            step = (left & -left).bit_length() - 1
            at += step
            for b in view.bins[at]:
                if not (has_source[b] & sb or has_cluster[b] & cb):
                    chosen = b
                    break
            left >>= step + 1
            at += 1
        if chosen < 0:
            chosen = len(room)
            room.append(capacity)
            has_source.append(0)
            has_cluster.append(0)
        else:
            for v in views.values():
                v.drop(room[chosen], chosen)
        out.append(chosen)
        offsets.append(capacity - room[chosen])
        room[chosen] -= size
        has_source[chosen] |= sb
        has_cluster[chosen] |= cb
        if room[chosen] >= max(least, 1):
            for v in views.values():
                if not (has_source[chosen] & v.avoid[0] or has_cluster[chosen] & v.avoid[1]):
                    v.add(room[chosen], chosen)
    return out, offsets


def pieces_of(docs: DataFrame, size, cluster, capacity: int, id_col: str, source_col: str) -> DataFrame:
    """One short row per piece: id, piece, size, source, cluster."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(size, F.lit(0)).cast("long").alias("_size"), F.col(source_col).cast("string").alias("source"), cluster.alias("cluster"))
    count = F.greatest(F.ceil(F.col("_size") / capacity), F.lit(1)).cast("int")
    cutup = rows.select("*", F.explode(F.sequence(F.lit(0), count - 1)).alias("piece"))
    return cutup.select("doc_id", "piece", F.least(F.lit(capacity).cast("long"), F.col("_size") - F.col("piece") * capacity).alias("size"), "source", "cluster")


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY, per_shard: int = PER_SHARD) -> DataFrame:
    """Each piece with its ``bin_id`` and ``bin_offset``; ``pieces`` has doc_id, piece, size, source, cluster."""
    rows = cut(pieces)
    shards = shards_for(rows.where("size > 0").count(), per_shard)
    dealt = rows.where("size > 0").withColumn("_shard", F.pmod(F.xxhash64(F.lit("shard"), "doc_id", "piece", "cluster"), F.lit(shards)))

    def packed(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["size", "doc_id", "piece", "cluster", "source"], ascending=[False, True, True, True, True], na_position="first", kind="stable")
        plain = lambda c: [None if pd.isna(x) else x for x in pdf[c]]
        bins, offsets = best_fit([int(x) for x in pdf["size"]], plain("source"), plain("cluster"), capacity)
        return pdf.assign(bin_id=[(int(key[0]) << 32) + b for b in bins], bin_offset=offsets)[["doc_id", "piece", "size", "source", "bin_id", "bin_offset"]]

    kind = dict(pieces.dtypes)["doc_id"]
    shape = f"doc_id {kind}, piece int, size long, source string, bin_id long, bin_offset long"
    done = dealt.groupBy("_shard").applyInPandas(packed, shape)
    empty = rows.where("size <= 0").select("doc_id", "piece", "size", "source", F.lit(None).cast("long").alias("bin_id"), F.lit(None).cast("long").alias("bin_offset"))
    return done.unionByName(empty)


def estimated_tokens(text):
    """Four bytes of text to a token, rounded up; a column of counted tokens can take its place."""
    return F.ceil(F.octet_length(F.coalesce(text, F.lit(""))) / 4).cast("long")


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, per_shard: int = PER_SHARD, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """Packs documents by estimated tokens; equal normalised texts form a duplicate cluster."""
    pieces = pieces_of(docs, estimated_tokens(F.col(text_col)), F.md5(normalised(F.col(text_col))), capacity, id_col, source_col)
    return pack_pieces(pieces, capacity, per_shard)


def bin_report(packed: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Number of bins, mean fill and pieces a bin."""
    bins = packed.where("bin_id is not null").groupBy("bin_id").agg(F.sum("size").alias("filled"), F.count("*").alias("pieces"))
    return bins.agg(F.count("*").alias("n_bins"), (F.sum("filled") / F.count("*") / capacity).alias("mean_fill"), F.avg("pieces").alias("mean_pieces"))
