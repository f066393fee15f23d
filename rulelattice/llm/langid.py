"""Language identification: averaged hashed subword embeddings with a linear softmax.

A text's subwords are the byte n-grams (lengths ``NGRAMS``) of its lower-cased UTF-8 bytes. Each is
hashed to a row of an embedding table; a text is the average of its rows, and a linear layer with
softmax scores the languages. Table and layer are trained together by stochastic gradient descent in
numpy on a bounded sample of labelled rows (``SAMPLE`` texts at most, shared evenly over the labels,
of ``LONGEST`` bytes each and ``SAMPLE_BYTES`` in all), which are documented limits of the fit alone; prediction reads whole texts
of all rows. A part of the sample that the descent does not see calibrates the scores (a temperature)
and sets the level below which a prediction is marked as rejected.

Edge cases: a null text, or one without a letter, is ``und`` with score 0; without any labelled row
every text is ``und``; repeated rows are predicted each; a null id counts as the text ``""`` for the
fold; an empty table gives an empty result.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

NGRAMS = (2, 3, 4)
BUCKET_BITS = 16
WIDTH = 16
SAMPLE = 6000
SAMPLE_BYTES = 24_000_000
#: Bytes of the longest text that the sample takes.
LONGEST = 1_000_000
EPOCHS = 3
RATE = 0.5
#: Share of calibration texts that the rejection level marks although they are right.
REJECTED_RIGHT = 0.005
#: Fixed value: prime multiplier of the hash.
PRIME = np.uint32(0x9E3779B1)


def folded(data: bytes) -> np.ndarray:
    """Bytes of a lower-cased text between blanks."""
    return np.frombuffer(b" " + data + b" ", np.uint8).astype(np.uint32)


def subwords(text: str) -> np.ndarray:
    """Bucket of every n-gram."""
    b = folded(text.lower().encode("utf-8", "surrogatepass"))
    found = []
    code = b
    for n in range(2, max(NGRAMS) + 1):
        code = (code[:-1] << np.uint32(8)) | b[n - 1 :] if n <= 4 else code[:-1] * PRIME + b[n - 1 :]
        if n in NGRAMS:
            found.append(((code + np.uint32(n)) * PRIME) >> np.uint32(32 - BUCKET_BITS))
    return np.concatenate(found)


@dataclass
class Model:
    labels: list[str]
    #: For each bucket what it adds to each label's score; the embedding times the linear layer.
    table: np.ndarray
    bias: np.ndarray
    temperature: float
    level: float

    def scores(self, text: str) -> np.ndarray:
        at = subwords(text)
        if len(at) > 1 << 14:
            total = np.bincount(at, minlength=len(self.table)).astype(np.float64) @ self.table
        else:
            total = self.table[at].sum(axis=0, dtype=np.float64)
        z = (total / max(len(at), 1) + self.bias) / self.temperature
        e = np.exp(z - z.max())
        return e / e.sum()

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        if not text or not self.labels or not has_letter(text):
            return "und", 0.0, True
        p = self.scores(text)
        best = int(p.argmax())
        return self.labels[best], float(p[best]), bool(p[best] < self.level)


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def train(texts: list[str], labels: list[str], seed: int = 1) -> Model:
    """Fits on four fifths of the texts and calibrates on the rest."""
    names = sorted(set(labels))
    if not names:
        return Model([], np.zeros((1 << BUCKET_BITS, 0), np.float32), np.zeros(0), 1.0, 1.0)
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(texts))
    held = order[: len(order) // 5]
    seen = order[len(order) // 5 :]
    target = np.array([names.index(x) for x in labels])
    bags = []
    for t in texts:
        at, n = np.unique(subwords(t), return_counts=True)
        bags.append((at, (n / max(n.sum(), 1)).astype(np.float32)))
    emb = rng.normal(0, 0.1, (1 << BUCKET_BITS, WIDTH)).astype(np.float32)
    out = rng.normal(0, 0.1, (WIDTH, len(names))).astype(np.float32)
    bias = np.zeros(len(names), np.float32)
    steps, done = EPOCHS * max(len(seen), 1), 0
    for _ in range(EPOCHS):
        for i in rng.permutation(seen):
            rate = RATE * (1 - done / steps)
            done += 1
            at, share = bags[i]
            if not len(at):
                continue
            mean = share @ emb[at]
            z = mean @ out + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[target[i]] -= 1
            back = out @ p
            out -= rate * np.outer(mean, p)
            bias -= rate * 0.1 * p
            # Rows of an average each get their share; scaled so that a text moves its rows as a whole.
            emb[at] -= (rate * 50 * share)[:, None] * back[None, :]
    model = Model(names, np.ascontiguousarray(emb @ out), bias.astype(np.float64), 1.0, 0.0)
    raw = np.array([np.log(np.maximum(model.scores(texts[i]), 1e-30)) for i in held]).reshape(len(held), len(names))
    if len(held):
        def loss(t: float) -> float:
            z = raw / t
            z = z - z.max(axis=1, keepdims=True)
            return float(np.mean(np.log(np.exp(z).sum(axis=1)) - z[np.arange(len(held)), target[held]]))
        model.temperature = float(min(np.geomspace(0.05, 20, 60), key=loss))
        final = np.array([model.scores(texts[i]) for i in held])
        right = final.argmax(axis=1) == target[held]
        if right.any():
            model.level = float(np.quantile(final.max(axis=1)[right], REJECTED_RIGHT))
    return model


def fold(id_col: str) -> Column:
    """0 to 3: CRC-32 of the id's decimal text, modulo 4."""
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), F.lit(4))


def training_sample(docs: DataFrame, id_col: str, text_col: str, lang_col: str) -> DataFrame:
    """At most ``SAMPLE`` labelled rows outside fold 2, chosen by a hash of their id, even over the labels.

    Each task first keeps its own share of every label, so that no label is gathered whole.
    """
    labelled = docs.where((fold(id_col) != 2) & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).alias("lang"), F.col(id_col).alias("id"), F.xxhash64(id_col, text_col).alias("place"))
    salted = labelled.withColumn("salt", F.pmod("place", F.lit(64)))
    by_salt = Window.partitionBy("lang", "salt").orderBy("place")
    first = salted.withColumn("n", F.row_number().over(by_salt)).where(f"n <= {SAMPLE // 64}")
    ranked = first.withColumn("n", F.row_number().over(Window.partitionBy("lang").orderBy("place")))
    return ranked.orderBy("n", "lang").limit(SAMPLE).select("place", "lang")


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """A model trained on the sample, which is collected: its rows and bytes are bounded (``SAMPLE``, ``SAMPLE_BYTES``)."""
    labelled = docs.where((fold(id_col) != 2) & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    place = F.xxhash64(id_col, text_col)
    chosen = training_sample(docs, id_col, text_col, lang_col).select("place").distinct()
    # Only sizes meet in one task; texts are read for those that stay within the bytes.
    sizes = labelled.select(place.alias("place"), F.octet_length(text_col).alias("size")).where(f"size <= {LONGEST}").join(F.broadcast(chosen), "place").dropDuplicates(["place"])  # SAMPLE rows at most
    running = F.sum("size").over(Window.orderBy("place").rowsBetween(Window.unboundedPreceding, -1))
    within = sizes.withColumn("before", running).where(F.coalesce("before", F.lit(0)) + F.col("size") <= SAMPLE_BYTES).select("place")
    rows = labelled.select(place.alias("place"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"))
    got = sorted(rows.join(F.broadcast(within), "place").dropDuplicates(["place"]).collect(), key=lambda r: r["place"])
    return train([r["text"] for r in got], [r["lang"] for r in got])


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``held_out``, ``lang_pred``, ``score`` and ``rejected``."""
    shared = docs.sparkSession.sparkContext.broadcast(pickle.dumps(model))  # the table's size is fixed by BUCKET_BITS and the labels
    kind = dict(docs.dtypes)[id_col]

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = pickle.loads(shared.value)
        for b in batches:
            out = [own.predict(t) for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array([x[0] for x in out], pa.string()), pa.array([x[1] for x in out], pa.float64()), pa.array([x[2] for x in out], pa.bool_())],
                [id_col, "held_out", "lang_pred", "score", "rejected"],
            )

    asked = docs.select(F.col(id_col), (fold(id_col) == 2).alias("held_out"), F.col(text_col))
    return asked.mapInArrow(rows, f"{id_col} {kind}, held_out boolean, lang_pred string, score double, rejected boolean")
