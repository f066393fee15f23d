"""SimHash near-duplicates that are verified: whole-text shingles at a Jaccard similarity.

A text's shingles are its runs of ``words`` words, each counted once. Two texts link if their shingles'
Jaccard similarity is ``ALIKE`` or more, and every link is compared on all shingles of both texts.

Candidates come from fingerprints of ``LANES`` times 64 bits: the first lane has the bits that more than half
of the shingle hashes have, the others those of the same hashes mixed anew. Texts meet in a table where they
agree in all of its drawn bits. The bits of a table grow with the logarithm of the number of texts, so that
a key has a bounded number of unrelated texts at any size, and the tables are as many as a pair at the
similarity ``ALIKE`` needs to meet with the chance ``RECALL``. Of the pairs that meet, those whose distances to any
pivot differ by more than ``RADIUS`` are discarded, then those that differ in more bits, and the others are verified.

Under the first ``EARLY`` tables texts are compared with one of their key only, and those links are joined to
components, so that very many near copies of a text do not cost all their pairs. Then all tables are searched
for links between components. The texts of a key are dealt to blocks and pairs of blocks to cells, except
pairs of blocks that the key's largest component fills. A cell looks for pairs that no earlier table brings together,
is sent the shingles of texts that have one, and hands on a spanning forest of the links it verifies.
So rows grow with texts and cells, not with the pairs of a group whose members are alike, yet less than ``ALIKE``.

Edge cases: texts without words (null, empty, blank) are alike; texts of fewer words than a shingle
are one shingle; rows repeated with an id keep one row each; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulelattice.llm.common import cut, set_aside, sifted
from rulelattice.llm.components import components
from rulelattice.llm.simhash import bit_counts, chosen, pivots

#: Jaccard similarity from which texts link, as numerator and denominator.
ALIKE = (4, 5)
WORDS = 5
LANES = 4
#: Bits in which two texts at the similarity may differ: of 256 they differ in 39 on average, with a standard deviation of about 6.
RADIUS = 70
PIVOTS = 4
#: Share of bits in which two texts at the similarity differ: the angle whose cosine is 8 / 9, by pi.
EDGE = math.acos(2 * ALIKE[0] / (ALIKE[0] + ALIKE[1])) / math.pi
#: Chance that two texts at the similarity meet in some table.
RECALL = 0.999
#: Unrelated texts that a key has on average.
CROWD = 64
#: Tables whose links bring copies together before all tables are searched.
EARLY = 8
#: Pairs that are verified together, on average.
CELL = 2048
#: Texts of a key that make a block, and shingles that a block holds, on average.
BLOCK = 256
HELD = 1_000_000
#: Rows that are handed on at once.
ROWS_AT_ONCE = 500_000
SEED = 42
PRINTS = [f"f{i}" for i in range(LANES)]
#: Columns of a text under a key, and in a cell.
KEYED = ["key", "th", *PRINTS, "n", "far", "own"]
CELLED = ["key", "i", "j", "block", *KEYED[1:]]


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """Hashes of a text's distinct shingles."""
    said = (text or "").encode("utf-8", "surrogatepass").lower().split()
    digest = xxhash.xxh64_intdigest
    return np.array(sorted({digest(b" ".join(said[i : i + words]), SEED) for i in range(max(1, len(said) - words + 1))}), np.uint64)


def lanes(hashes: np.ndarray) -> list[int]:
    """Fingerprints of one set of hashes, signed."""
    out = []
    for lane in range(LANES):
        mixed = hashes
        if lane:
            # Increment and multipliers of a public 64-bit mixing function.
            mixed = hashes + np.uint64(lane * 0x9E3779B97F4A7C15 % (1 << 64))
            mixed = (mixed ^ (mixed >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            mixed = (mixed ^ (mixed >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            mixed = mixed ^ (mixed >> np.uint64(31))
        out.append(int(np.packbits(2 * bit_counts(mixed) > len(hashes), bitorder="little").view(np.int64)[0]))
    return out


def _prints(docs: DataFrame, words: int, text_col: str) -> DataFrame:
    """(th, f0, ..., n): every text's hash, fingerprints and number of shingles, once."""
    names = [*PRINTS, "n"]

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = (shingles(text.as_py(), words) for text in batch.column(1))
            table = np.array([[*lanes(hashes), len(hashes)] for hashes in found], np.int64).reshape(-1, len(names))
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(np.ascontiguousarray(table[:, i])) for i in range(len(names))]], ["th", *names])

    made = docs.select(F.xxhash64(text_col).alias("th"), F.col(text_col)).mapInArrow(rows, "th long, " + ", ".join(f"{c} long" for c in names))
    return made.groupBy("th").agg(*[F.min(c).alias(c) for c in names])


def tables_for(texts: int) -> tuple[int, int]:
    """Number of tables and bits of each for so many texts."""
    bits = max(4, math.ceil(math.log2(max(texts, 2) / CROWD)))
    return math.ceil(math.log(1 - RECALL) / math.log(1 - (1 - EDGE) ** bits)), bits


def drawn_bits(tables: int, bits: int) -> np.ndarray:
    """The bits of each table, among those of all lanes."""
    rng = np.random.default_rng(11)
    return np.stack([rng.choice(64 * LANES, bits, replace=False) for _ in range(tables)])


def table_keys(prints: np.ndarray, drawn: np.ndarray) -> np.ndarray:
    """Keys of fingerprints, a row of lanes each, in every table; the table stands above the bits of a key."""
    tables, bits = drawn.shape
    shown = np.unpackbits(np.ascontiguousarray(prints).view(np.uint8), axis=1, bitorder="little")
    return shown[:, drawn.reshape(-1)].reshape(len(prints), tables, bits) @ (np.int64(1) << np.arange(bits, dtype=np.int64)) + (np.arange(tables, dtype=np.int64) << bits)


def _keyed(prints: DataFrame, drawn: np.ndarray) -> DataFrame:
    """(key, th, f0, ..., n, far, own): a row for each table, with the distances to the pivots, 16 bits each;
    ``own`` is the text's component so far."""
    refs = pivots(PIVOTS * LANES).reshape(LANES, PIVOTS)
    used = len(drawn)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            step = max(1, ROWS_AT_ONCE // used)
            for start in range(0, whole.num_rows, step):
                th, n, own, *fs = (c.to_numpy(zero_copy_only=False) for c in whole.slice(start, step).columns)
                away = sum(np.bitwise_count(f.view(np.uint64)[:, None] ^ refs[i][None, :]).astype(np.int64) for i, f in enumerate(fs))
                far = away @ (np.int64(1) << (16 * np.arange(PIVOTS, dtype=np.int64)))
                held = [table_keys(np.stack(fs, axis=1), drawn).reshape(-1), *[np.repeat(c, used) for c in (th, *fs, n, far, own)]]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in held], KEYED)

    return prints.select("th", "n", "own", *PRINTS).mapInArrow(rows, ", ".join(f"{c} long" for c in KEYED))


def _met(rows: DataFrame, others: DataFrame) -> DataFrame:
    """Pairs (a, b) of rows and others with one key, of different components, that the pivots and then the bits let pass.

    Both sides are dealt anew, so hot keys can be split.
    """
    other = others.toDF(*[f"o_{c}" for c in others.columns]).withColumn("o_key", F.shiftleft("o_key", 0))
    pivot = lambda c, i: F.shiftright(c, 16 * i).bitwiseAND(F.lit(65535))
    near = F.col("own") != F.col("o_own")
    for i in range(PIVOTS):
        near &= F.abs(pivot("far", i) - pivot("o_far", i)) <= RADIUS
    near &= sum((F.bit_count(F.col(f).bitwiseXOR(F.col(f"o_{f}"))) for f in PRINTS), F.lit(0)) <= RADIUS
    return rows.join(other, F.col("key") == F.col("o_key")).where(near).select(F.least("th", "o_th").alias("a"), F.greatest("th", "o_th").alias("b"))


def _cells(keyed: DataFrame) -> DataFrame:
    """(key, i, j, block, th, ...): the rows of every cell, a pair of blocks i <= j of a key's texts.

    Where a key's largest component fills a block, its texts have blocks of their own, after the others; pairs
    of those blocks have no cell. A key of one component has none at all.
    """
    sizes = keyed.groupBy("key", "own").agg(F.count("*").alias("c"), F.sum("n").alias("s"))
    of_key = sizes.groupBy("key").agg(F.max(F.struct("c", "s", "own")).alias("most"), F.sum("c").alias("c"), F.sum("s").alias("s")).where("c > most.c")
    blocks = lambda c, s: F.ceil(F.greatest(c / F.lit(BLOCK), s / F.lit(HELD)))
    led = F.when((F.col("most.c") > BLOCK) | (F.col("most.s") > HELD), blocks(F.col("most.c"), F.col("most.s"))).otherwise(0)
    rest = blocks(F.col("c") - F.when(led > 0, F.col("most.c")).otherwise(0), F.col("s") - F.when(led > 0, F.col("most.s")).otherwise(0))
    plan = of_key.select("key", F.col("most.own").alias("_lead"), rest.alias("_open"), led.alias("_led"))
    placed = keyed.join(plan.select(F.shiftleft("key", 0).alias("_k"), "_lead", "_open", "_led"), F.col("key") == F.col("_k"))
    dealt = F.xxhash64("th", F.lit(1))
    leads = (F.col("own") == F.col("_lead")) & (F.col("_led") > 0)
    block = F.when(leads, F.col("_open") + F.pmod(dealt, F.col("_led"))).otherwise(F.pmod(dealt, F.col("_open")))
    last = F.when(leads, F.col("_open")).otherwise(F.col("_open") + F.col("_led")) - 1
    sent = placed.withColumn("block", block).withColumn("to", F.explode(F.sequence(F.lit(0).cast("long"), last)))
    return sent.select("key", F.least("block", "to").alias("i"), F.greatest("block", "to").alias("j"), "block", *KEYED[1:])


def cell_pairs(rows: np.ndarray, drawn: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of positions in one cell, a row of ``CELLED`` each, that may be alike: of two components, of sizes that
    allow it, let pass by the pivots and then by the bits, and brought together by no earlier table."""
    key, i, j = rows[0, :3].tolist()
    left = np.flatnonzero(rows[:, 3] == i)
    right = left if i == j else np.flatnonzero(rows[:, 3] == j)
    at = {c: (rows[left, k], rows[right, k]) for k, c in enumerate(CELLED)}
    (own, o_own), (n, o_n), (far, o_far) = (at[c] for c in ("own", "n", "far"))
    near = (own[:, None] != o_own) & (ALIKE[1] * np.minimum(n[:, None], o_n) >= ALIKE[0] * np.maximum(n[:, None], o_n))
    for p in range(PIVOTS):
        d, o_d = (far >> 16 * p) & 65535, (o_far >> 16 * p) & 65535
        near &= np.abs(d[:, None] - o_d) <= RADIUS
    a, b = (s[x] for s, x in zip((left, right), np.nonzero(near), strict=True))
    if i == j:
        a, b = a[a < b], b[a < b]
    prints = rows[:, CELLED.index("f0") : CELLED.index("f0") + LANES]
    close = np.bitwise_count((prints[a] ^ prints[b]).view(np.uint64)).sum(axis=1, dtype=np.int64) <= RADIUS
    a, b = a[close], b[close]
    if not len(a):
        return a, b
    before = table_keys(prints, drawn)[:, : key >> drawn.shape[1]]
    new = ~(before[a] == before[b]).any(axis=1)
    return a[new], b[new]


def _partnered(drawn: np.ndarray):
    """The rows of cells, which come sorted, that have a partner in their cell."""
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def kept(cells: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
            found = [cell[np.unique(np.concatenate(cell_pairs(cell, drawn)))] for cell in cells if len(cell) > 1]
            if found:
                table = np.concatenate(found)
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(table[:, k])) for k in range(len(CELLED))], CELLED)

        held = np.empty((0, len(CELLED)), np.int64)
        for batch in batches:
            held = np.concatenate([held, np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns], axis=1)])
            *whole, held = np.split(held, np.flatnonzero((held[1:, :3] != held[:-1, :3]).any(axis=1)) + 1)
            yield from kept(whole)
        yield from kept([held])

    return rows


def _forest_of(drawn: np.ndarray):
    """Links (a, b) that span what is alike in one cell; its rows have each text's shingles, sorted as unsigned."""
    def rows(cell: pa.Table) -> pa.Table:
        table = np.stack([cell[c].to_numpy() for c in CELLED], axis=1)
        held = [s.values.to_numpy().view(np.uint64) for s in cell["s"]]
        th, label = table[:, CELLED.index("th")], table[:, CELLED.index("own")].copy()
        a, b = cell_pairs(table, drawn)
        links = []
        for x in np.unique(a).tolist():
            others = b[a == x]
            # Who has been linked by now, directly or not, is not compared again.
            others = others[label[others] != label[x]]
            if not len(others):
                continue
            own, sizes = held[x], np.array([len(held[y]) for y in others.tolist()])
            said = np.concatenate([held[y] for y in others.tolist()])
            both = np.add.reduceat(own[np.minimum(np.searchsorted(own, said), len(own) - 1)] == said, np.r_[0, np.cumsum(sizes)[:-1]], dtype=np.int64)
            for y in others[ALIKE[1] * both >= ALIKE[0] * (len(own) + sizes - both)].tolist():
                if label[y] != label[x]:
                    label[label == label[y]] = label[x]
                    links.append((th[x], th[y]))
        out = np.array(links, np.int64).reshape(-1, 2)
        return pa.table({"a": out.min(axis=1), "b": out.max(axis=1)})

    return rows


def _linked(keyed: DataFrame, drawn: np.ndarray, docs: DataFrame, words: int, text_col: str) -> DataFrame:
    """Links (a, b) that, with those within components, span what is alike under the keys."""
    long = ", ".join(f"{c} long" for c in CELLED)
    cells = _cells(keyed).repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")
    asked = cut(cells.mapInArrow(_partnered(drawn), long))
    sets = cut(_sets(docs, asked, words, text_col))
    sent = asked.join(sets.select(F.col("th").alias("_t"), "s"), F.col("th") == F.col("_t")).select(*CELLED, "s")
    return sent.groupBy("key", "i", "j").applyInArrow(_forest_of(drawn), "a long, b long")


def _sets(docs: DataFrame, asked: DataFrame, words: int, text_col: str) -> DataFrame:
    """(th, s): the shingles of the texts ``asked`` for, sorted as unsigned, once each."""
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ths, found, held = [], [], 0
            for th, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ths.append(th)
                found.append(shingles(text.as_py(), words).view(np.int64))
                held += len(found[-1])
                if held >= ROWS_AT_ONCE:
                    yield pa.RecordBatch.from_arrays([pa.array(ths, pa.int64()), pa.array(found, pa.list_(pa.int64()))], ["th", "s"])
                    ths, found, held = [], [], 0
            if ths:
                yield pa.RecordBatch.from_arrays([pa.array(ths, pa.int64()), pa.array(found, pa.list_(pa.int64()))], ["th", "s"])

    texts, _ = sifted(docs.select(F.xxhash64(text_col).alias("th"), F.col(text_col).alias("t")), F.col("th"), asked.select("th"))
    texts = texts.join(asked.select("th").distinct(), "th", "left_semi").dropDuplicates(["th"])
    return texts.mapInArrow(rows, "th long, s array<long>")


def _alike(pairs: DataFrame, docs: DataFrame, words: int, text_col: str) -> DataFrame:
    """The pairs (a, b) that are alike on all their shingles.

    Pairs are dealt to square cells of about ``CELL``, by a block of texts for either side, so that a text's shingles
    are sent once to a cell and not once for each of its pairs: a group of m texts costs m sets for each block.
    """
    pairs = cut(pairs.distinct())
    blocks = max(1, math.ceil(math.sqrt(pairs.count() / CELL)))
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(blocks))
    placed = pairs.withColumn("cell", block("a") * blocks + block("b"))
    # A text with very many partners fills its cells: those are parted by pairs.
    full = placed.groupBy("cell").agg(F.count("*").alias("_n")).where(F.col("_n") > 4 * CELL).select(F.shiftleft("cell", 0).alias("_c"), F.ceil(F.col("_n") / CELL).alias("_parts"))
    part = F.pmod(F.xxhash64("b", "a"), F.coalesce("_parts", F.lit(1)))
    placed = cut(placed.join(full, F.col("cell") == F.col("_c"), "left").select("a", "b", "cell", part.alias("part")))
    asked = placed.select(F.explode(F.array("a", "b")).alias("th"), "cell", "part").distinct()
    sets = cut(_sets(docs, asked, words, text_col))
    sent = asked.join(sets.select(F.col("th").alias("_t"), "s"), F.col("th") == F.col("_t")).select(F.shiftleft("cell", 0).alias("to"), F.shiftleft("part", 0).alias("of"), "th", "s")
    return placed.groupBy("cell", "part").cogroup(sent.groupBy("to", "of")).applyInArrow(_verified, "a long, b long")


def _verified(pairs: pa.Table, sent: pa.Table) -> pa.Table:
    """The pairs of one cell that are alike; ``sent`` has each text's shingles, sorted as unsigned, once."""
    sent = sent.combine_chunks()
    th, held = sent["th"].to_numpy(), sent["s"].combine_chunks()
    if isinstance(held, pa.ChunkedArray):
        held = held.chunk(0)
    starts, values = held.offsets.to_numpy(), held.values.to_numpy().view(np.uint64)
    order = np.argsort(th)
    a, b = (order[np.searchsorted(th[order], pairs[c].to_numpy())] for c in ("a", "b"))
    n = np.diff(starts)
    fits = np.flatnonzero(ALIKE[1] * np.minimum(n[a], n[b]) >= ALIKE[0] * np.maximum(n[a], n[b]))
    fits = fits[np.argsort(a[fits], kind="stable")]
    alike = []
    for run in np.split(fits, np.flatnonzero(np.diff(a[fits])) + 1) if len(fits) else ():
        own = values[starts[a[run[0]]] : starts[a[run[0]] + 1]]
        others = np.concatenate([values[starts[x] : starts[x + 1]] for x in b[run].tolist()])
        found = own[np.minimum(np.searchsorted(own, others), len(own) - 1)] == others
        both = np.add.reduceat(found, np.r_[0, np.cumsum(n[b[run]])[:-1]], dtype=np.int64)
        alike.append(run[ALIKE[1] * both >= ALIKE[0] * (len(own) + n[b[run]] - both)])
    return pairs.select(["a", "b"]).take(pa.array(np.concatenate(alike) if alike else np.empty(0, np.int64)))


def across(h: np.ndarray, root: np.ndarray, th: np.ndarray, n: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs with equal ``h`` and different roots whose sizes allow a link, of rows that one task holds; in blocks."""
    order = np.lexsort((root, h))
    h, root, th, n = h[order], root[order], th[order], n[order]
    if not len(h):
        return
    def ends(new: np.ndarray) -> np.ndarray:
        starts = np.flatnonzero(np.r_[True, new])
        return np.repeat(np.r_[starts[1:], len(h)], np.diff(np.r_[starts, len(h)]))
    other = h[1:] != h[:-1]
    first = ends(other | (root[1:] != root[:-1]))
    reach = ends(other) - first
    total = np.cumsum(reach)
    at = 0
    while at < len(h):
        done = total[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(total, done + ROWS_AT_ONCE, "right")))
        r = reach[at:to]
        a = np.repeat(np.arange(at, to), r)
        b = np.repeat(first[at:to], r) + np.arange(len(a)) - np.repeat(np.cumsum(r) - r, r)
        fits = ALIKE[1] * np.minimum(n[a], n[b]) >= ALIKE[0] * np.maximum(n[a], n[b])
        yield th[a[fits]], th[b[fits]]
        at = to


def near_roots(docs: DataFrame, words: int = WORDS, text_col: str = "text") -> DataFrame:
    """(node, root) for every text hash that links to another; root is its component's smallest hash."""
    prints = cut(_prints(docs, words, text_col))
    drawn = drawn_bits(*tables_for(prints.count()))
    alone = _keyed(prints.withColumn("own", F.col("th")), drawn[:EARLY])
    first = alone.groupBy("key").agg(F.min("th").alias("th"), F.count("*").alias("_n"), *[F.min_by(c, "th").alias(c) for c in KEYED if c not in ("key", "th")]).where("_n > 1").drop("_n")
    links = cut(_alike(_met(alone, first), docs, words, text_col))
    roots = components(links)
    rooted = prints.join(roots.select(F.col("node").alias("_n"), "root"), F.col("th") == F.col("_n"), "left").withColumn("own", F.coalesce("root", "th"))
    more = cut(_linked(_keyed(rooted, drawn), drawn, docs, words, text_col))
    return components(links.unionByName(more)) if more.head(1) else roots


def one_of_each(docs: DataFrame, words: int = WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each component, the one with the smallest id (a null id is last), with all its columns."""
    own, name = set_aside(docs)
    id_col, text_col = name(id_col), name(text_col)
    rows = own.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("th"))
    roots = near_roots(own, words, text_col).select(F.col("node").alias("_n"), "root")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), F.col("doc_id").alias("id"), F.col("th").alias("th")))
    named = rows.join(roots, F.col("th") == F.col("_n"), "left").groupBy(F.coalesce("root", "th").alias("root")).agg(first.alias("least"))
    return chosen(own, rows, named, id_col, text_col).toDF(*docs.columns)
