"""Quality scores by hashed word n-gram logistic regression.

Features are hashed one- and two-word grams of two spellings of each text: the
lower-cased words and their shapes (runs of upper case, lower case and digits
shrunk to one sign; a word equal to its predecessor has a shape of its own).
Each of the four families is a distribution over hashed grams, so a score is a
sparse dot product of gram shares and weights.  Weights come from
follow-the-regularised-leader updates, one document at a time, over a bounded
sample of labelled documents.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .textbatch import NON_BLANK, Words, gram_hashes, mix, segment_hashes, slices

_SHAPES = np.arange(256, dtype=np.uint8)
_SHAPES[65:91] = ord("A")
_SHAPES[97:123] = ord("a")
_SHAPES[128:] = ord("a")
_SHAPES[48:58] = ord("0")
_FAMILIES = 4


@dataclass(frozen=True)
class FtrlSettings:
    """bits: log2 of the weights (fixed size); sample: most labelled documents to learn from;
    alpha, beta, l1, l2: the update's constants; epochs, seed."""

    bits: int = 18
    sample: int = 4000
    alpha: float = 0.3
    beta: float = 1.0
    l1: float = 0.002
    l2: float = 0.0005
    scale: float = 8.0
    epochs: int = 6
    seed: int = 5


def _shape_hashes(raw: np.ndarray, words: Words) -> np.ndarray:
    kind = _SHAPES[raw]
    inside = NON_BLANK[raw]
    kind = kind[inside]
    lengths = words.ends - words.starts
    heads = np.cumsum(lengths) - lengths
    turn = np.ones(len(kind), bool)
    turn[1:] = kind[1:] != kind[:-1]
    turn[heads] = True
    hashes = segment_hashes(kind[turn], np.add.reduceat(turn, heads, dtype=np.int64))
    again = np.zeros(len(hashes), bool)
    again[1:] = words.hashes[1:] == words.hashes[:-1]
    again[words.rows[:-1][words.rows[:-1] < len(hashes)]] = False
    return np.where(again, mix(hashes), hashes)


def features(raw: np.ndarray, borders: np.ndarray, bits: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each family: weight index of every gram, and the gram range of each row."""
    words = Words(raw, borders, NON_BLANK)
    shapes = _shape_hashes(raw, words) if len(words.hashes) else words.hashes
    out = []
    for family, (hashes, n) in enumerate(((words.hashes, 1), (words.hashes, 2), (shapes, 1), (shapes, 2))):
        grams, _, rows = gram_hashes(hashes, words.rows, n)
        out.append(((mix(grams + np.uint64(family + 1)) >> np.uint64(64 - bits)).astype(np.int32), rows))
    return out


def _feature_kernel(bits: int, scale: float):
    def run(batches):
        for batch in batches:
            for part, raw, borders in slices(batch, "text"):
                families = features(raw, borders, bits)
                index, value = [], []
                for row in range(part.num_rows):
                    places, shares = [], []
                    for grams, rows in families:
                        own, counts = np.unique(grams[rows[row] : rows[row + 1]], return_counts=True)
                        places.append(own)
                        shares.append(counts * (scale / max(1, counts.sum())))
                    index.append(np.concatenate(places))
                    value.append(np.concatenate(shares).astype(np.float32))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(1), pa.array(index, pa.list_(pa.int32())), pa.array(value, pa.list_(pa.float32()))],
                    names=["doc_id", "label", "places", "shares"],
                )

    return run


class Ftrl:
    """Per-coordinate follow-the-regularised-leader logistic regression."""

    def __init__(self, settings: FtrlSettings):
        self.s = settings
        self.z = np.zeros(1 << settings.bits)
        self.n = np.zeros(1 << settings.bits)
        self.bias_z = self.bias_n = 0.0

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n, s = self.z[at], self.n[at], self.s
        live = np.abs(z) > s.l1
        return np.where(live, -(z - np.sign(z) * s.l1) / ((s.beta + np.sqrt(n)) / s.alpha + s.l2), 0.0)

    def bias(self) -> float:
        return -self.bias_z / ((self.s.beta + self.bias_n**0.5) / self.s.alpha)

    def learn(self, places: np.ndarray, shares: np.ndarray, label: int) -> float:
        w, b = self.weights(places), self.bias()
        p = 1 / (1 + np.exp(-np.clip(w @ shares + b, -35, 35)))
        g = (p - label) * shares
        grown = np.sqrt(self.n[places] + g * g)
        np.add.at(self.z, places, g - (grown - np.sqrt(self.n[places])) / self.s.alpha * w)
        np.add.at(self.n, places, g * g)
        e = p - label
        self.bias_z += e - ((self.bias_n + e * e) ** 0.5 - self.bias_n**0.5) / self.s.alpha * b
        self.bias_n += e * e
        return p


@dataclass
class QualityModel:
    weights: np.ndarray
    bias: float
    bits: int
    scale: float


def train(spark: SparkSession, docs: DataFrame, labels: DataFrame, settings: FtrlSettings = FtrlSettings()) -> QualityModel:
    """Learn from at most ``sample`` documents whose remainder is not 0.

    Documents with several labels count with the largest; null labels or texts
    teach nothing.  With nothing to learn from all scores are 0.5.
    """
    usable = labels.where((F.crc32(F.col("doc_id").cast("string")) % 5 != 0) & F.col("quality").isNotNull())
    chosen = usable.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").cast("int").alias("label"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(settings.sample)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    rows = texts.join(F.broadcast(chosen), "doc_id").select("doc_id", "label", "text")  # at most `sample` ids
    got = rows.mapInArrow(_feature_kernel(settings.bits, settings.scale), "doc_id long, label int, places array<int>, shares array<float>").toArrow()
    order = np.lexsort((got.column("doc_id").to_numpy(),))
    label = got.column("label").to_numpy()
    places, shares = got.column("places").combine_chunks(), got.column("shares").combine_chunks()
    ends = places.offsets.to_numpy()
    flat_places, flat_shares = places.values.to_numpy(), shares.values.to_numpy()
    rng = np.random.Generator(np.random.PCG64(settings.seed))
    model = Ftrl(settings)
    for _ in range(settings.epochs):
        for i in rng.permutation(order):
            lo, hi = ends[i], ends[i + 1]
            model.learn(flat_places[lo:hi], flat_shares[lo:hi].astype(np.float64), int(label[i]))
    return QualityModel(model.weights(), model.bias(), settings.bits, settings.scale)


def _score_kernel(shared):
    def run(batches):
        model: QualityModel = shared.value
        for batch in batches:
            for part, raw, borders in slices(batch, "text"):
                total = np.full(part.num_rows, model.bias)
                for grams, rows in features(raw, borders, model.bits):
                    counts = np.diff(rows)
                    full = counts > 0
                    if full.any():
                        total[full] += np.add.reduceat(model.weights[grams], rows[:-1][full]) / counts[full] * model.scale
                score = 1 / (1 + np.exp(-np.clip(total, -35, 35)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(score)], names=["doc_id", "score"])

    return run


def score_documents(spark: SparkSession, docs: DataFrame, model: QualityModel, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted of every whole text.

    Null and empty texts score the model's bias; repeated rows score alike; an
    empty table gives no rows; extra columns are ignored.
    """
    shared = spark.sparkContext.broadcast(model)  # 2**bits floats
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    scored = rows.mapInArrow(_score_kernel(shared), "doc_id long, score double")
    held = (F.crc32(F.col("doc_id").cast("string")) % 5 == 0).alias("held_out")
    return scored.select("doc_id", held, "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def classify(spark: SparkSession, docs: DataFrame, labels: DataFrame, settings: FtrlSettings = FtrlSettings()) -> DataFrame:
    return score_documents(spark, docs, train(spark, docs, labels, settings))
