"""Language identification by a bidirectional gated recurrent network over bytes.

The network reads a text as lower-cased letters with one space between runs of
letters, so it sees how words follow each other, not words alone.  The byte
stream of a document is cut into segments of ``segment`` bytes; in each the
network runs forwards and backwards, labels every byte position with language
probabilities, and a document's probabilities are the mean over all positions of
its whole text.

Training is backpropagation through time in numpy on the driver, on a bounded,
documented sample: ``docs_per_language`` documents and ``segments`` segments of
each language; no language is left out.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .textbatch import byte_class, slices
from .workspace import Workspace

LETTERS = byte_class(lambda b: 0x61 <= b <= 0x7A or b >= 0x80)


#: Byte that fills short segments of a batch: it leaves the state as it is and is never labelled.
PAD, SPACE = 0, 0x20


@dataclass(frozen=True)
class GruSettings:
    """hidden: units a direction; segment: bytes of a segment; docs_per_language, segments (both
    for each language): bounds of the training sample; epochs, batch, rate, seed: training."""

    hidden: int = 8
    segment: int = 96
    docs_per_language: int = 300
    segments: int = 600
    epochs: int = 7
    batch: int = 96
    rate: float = 0.03
    seed: int = 11


def _sigmoid(x: np.ndarray) -> np.ndarray:
    x *= 0.5
    np.tanh(x, out=x)
    x += 1.0
    x *= 0.5
    return x


class ByteGru:
    """Parameters and passes; sequences of one call all have the same length."""

    NAMES = ("table_f", "recur_f", "bias_f", "table_b", "recur_b", "bias_b", "out", "out_bias")

    def __init__(self, hidden: int, classes: int, seed: int):
        rng = np.random.Generator(np.random.PCG64(seed))
        draw = lambda *shape: (rng.standard_normal(shape) * (0.5 / np.sqrt(shape[0] if shape[0] != 256 else 4))).astype(np.float32)
        self.hidden = hidden
        self.p = {
            "table_f": draw(256, 3 * hidden), "recur_f": draw(hidden, 3 * hidden), "bias_f": np.zeros(hidden, np.float32),
            "table_b": draw(256, 3 * hidden), "recur_b": draw(hidden, 3 * hidden), "bias_b": np.zeros(hidden, np.float32),
            "out": draw(2 * hidden, classes), "out_bias": np.zeros(classes, np.float32),
        }

    def _run(self, side: str, seq: np.ndarray, keep: bool):
        table, recur, bias, H = self.p[f"table_{side}"], self.p[f"recur_{side}"], self.p[f"bias_{side}"], self.hidden
        h = np.zeros((len(seq), H), table.dtype)
        states, saved = [], []
        for t in range(seq.shape[1]):
            x, g = table[seq[:, t]], h @ recur
            gates = _sigmoid(x[:, : 2 * H] + g[:, : 2 * H])
            z, r = gates[:, :H], gates[:, H:]
            inner = g[:, 2 * H :] + bias
            n = np.tanh(x[:, 2 * H :] + r * inner)
            new = n + z * (h - n)
            if keep:
                saved.append((h, z, r, inner, n))
            h = new
            states.append(h)
        return states, saved

    def probabilities(self, seq: np.ndarray) -> tuple[np.ndarray, tuple]:
        """Class probabilities of each position: (sequences, positions, classes)."""
        return self._forward(seq, False)[0]

    def _forward(self, seq: np.ndarray, keep: bool):
        forward, saved_f = self._run("f", seq, keep)
        backward, saved_b = self._run("b", seq[:, ::-1], keep)
        both = np.concatenate([np.stack(forward, 1), np.stack(backward[::-1], 1)], 2)
        logits = both @ self.p["out"] + self.p["out_bias"]
        logits -= logits.max(2, keepdims=True)
        np.exp(logits, out=logits)
        logits /= logits.sum(2, keepdims=True)
        return logits, both, saved_f, saved_b

    def loss_and_gradients(self, seq: np.ndarray, label: np.ndarray, weight: np.ndarray) -> tuple[float, dict]:
        """Weighted mean cross-entropy over positions and its gradients, through time."""
        probs, both, saved_f, saved_b = self._forward(seq, True)
        B, L, _ = probs.shape
        scale = (weight / (weight.sum() * L)).astype(probs.dtype)
        picked = probs[np.arange(B), :, label]
        loss = float(-(np.log(picked + 1e-12) * scale[:, None]).sum())
        d = probs.copy()
        d[np.arange(B), :, label] -= 1
        d *= scale[:, None, None]
        flat = both.reshape(B * L, -1)
        grads = {"out": flat.T @ d.reshape(B * L, -1), "out_bias": d.sum((0, 1))}
        d_both = d @ self.p["out"].T
        H = self.hidden
        self._through_time("f", seq, saved_f, d_both[:, :, :H], grads)
        self._through_time("b", seq[:, ::-1], saved_b, d_both[:, ::-1, H:], grads)
        return loss, grads

    def _through_time(self, side: str, seq: np.ndarray, saved: list, d_states: np.ndarray, grads: dict) -> None:
        recur = self.p[f"recur_{side}"]
        B, L = seq.shape
        carry = np.zeros((B, self.hidden), recur.dtype)
        d_recur, d_bias, d_inputs = np.zeros_like(recur), np.zeros(self.hidden, recur.dtype), []
        for t in range(L - 1, -1, -1):
            h, z, r, inner, n = saved[t]
            d = d_states[:, t] + carry
            d_n = d * (1 - z) * (1 - n * n)
            d_z = d * (h - n) * z * (1 - z)
            d_r = d_n * inner * r * (1 - r)
            d_inner = d_n * r
            d_inputs.append(np.concatenate([d_z, d_r, d_n], 1))
            d_g = np.concatenate([d_z, d_r, d_inner], 1)
            d_recur += h.T @ d_g
            d_bias += d_inner.sum(0)
            carry = d * z + d_g @ recur.T
        d_table = np.zeros_like(self.p[f"table_{side}"])
        np.add.at(d_table, seq[:, ::-1].T.ravel(), np.concatenate(d_inputs, 0))
        grads |= {f"recur_{side}": d_recur, f"bias_{side}": d_bias, f"table_{side}": d_table}

    def fit(self, words: list[bytes], labels: np.ndarray, weights: np.ndarray, settings: GruSettings) -> None:
        """Adam over batches of equal length, in a seeded order."""
        rng = np.random.Generator(np.random.PCG64(settings.seed + 1))
        lengths = np.array([len(w) for w in words])
        groups = {n: np.flatnonzero(lengths == n) for n in np.unique(lengths)}
        packed = {n: np.frombuffer(b"".join(words[i] for i in at), np.uint8).reshape(len(at), n) for n, at in groups.items()}
        first = {k: np.zeros_like(v) for k, v in self.p.items()}
        second = {k: np.zeros_like(v) for k, v in self.p.items()}
        turn, total = 0, settings.epochs * sum(-(-len(at) // settings.batch) for at in groups.values())
        for _ in range(settings.epochs):
            batches = []
            for n, at in groups.items():
                order = rng.permutation(len(at))
                batches += [(n, order[lo : lo + settings.batch]) for lo in range(0, len(at), settings.batch)]
            for i in rng.permutation(len(batches)):
                n, rows = batches[i]
                at = groups[n][rows]
                _, grads = self.loss_and_gradients(packed[n][rows], labels[at], weights[at])
                turn += 1
                rate = settings.rate * (1 - 0.9 * turn / total)
                for k, g in grads.items():
                    first[k] += 0.1 * (g - first[k])
                    second[k] += 0.001 * (g * g - second[k])
                    self.p[k] -= rate * (first[k] / (1 - 0.9**turn)) / (np.sqrt(second[k] / (1 - 0.999**turn)) + 1e-8)


@dataclass
class LanguageModel:
    network: ByteGru
    languages: list[str]
    settings: GruSettings


def letter_stream(raw: np.ndarray, borders: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Letters of lower-cased rows with one space after each run of them, and the row borders."""
    inside = LETTERS[raw]
    keep = inside.copy()
    if len(raw):
        after = np.zeros(len(raw), bool)
        after[1:] = inside[:-1] & ~inside[1:]
        after[borders[:-1][borders[:-1] < borders[1:]]] = False  # a row's first byte follows nothing
        keep |= after
    data = np.where(inside, raw, np.uint8(SPACE))[keep]
    return data, np.concatenate(([0], np.cumsum(keep)))[borders]


def cut_segments(rows: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and length of each segment of a stream's rows, and the segment range of each row."""
    lengths = np.diff(rows)
    pieces = -(-lengths // size)
    ranges = np.concatenate(([0], np.cumsum(pieces)))
    place = np.arange(int(ranges[-1])) - np.repeat(ranges[:-1], pieces)
    starts = np.repeat(rows[:-1], pieces) + place * size
    return starts, np.minimum(size, np.repeat(rows[1:], pieces) - starts), ranges


class SegmentLabeller:
    """Summed position probabilities of segments by a trained network, in large batches.

    The arrays are kept units by sequences, so that each step runs over contiguous memory.
    """

    BATCH = 2048

    def __init__(self, network: ByteGru):
        p, H = network.p, network.hidden
        self.hidden = H
        self.sides = []
        for side in "fb":
            table = p[f"table_{side}"].T.copy()
            table[:H, PAD], table[H:, PAD] = 1e4, 0.0  # the update gate is shut: the state stays
            self.sides.append((table, p[f"recur_{side}"].T.copy(), p[f"bias_{side}"][:, None].copy()))
        self.out, self.out_bias = p["out"].T.copy(), p["out_bias"][:, None].copy()

    def _states(self, side: int, steps: np.ndarray) -> np.ndarray:
        (table, recur, bias), H = self.sides[side], self.hidden
        length, width = steps.shape
        states = np.empty((length, H, width), np.float32)
        h = np.zeros((H, width), np.float32)
        for t in range(length) if side == 0 else range(length - 1, -1, -1):
            x = table[:, steps[t]]
            g = recur @ h
            gates = _sigmoid(x[: 2 * H] + g[: 2 * H])
            n = g[2 * H :]
            n += bias
            n *= gates[H:]
            n += x[2 * H :]
            np.tanh(n, out=n)
            h = h - n
            h *= gates[:H]
            h += n
            states[t] = h
        return states

    def sums(self, data: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """(segments, classes): probabilities summed over each segment's positions."""
        total = np.empty((len(starts), len(self.out)))
        order = np.argsort(lengths, kind="stable")
        for lo in range(0, len(order), self.BATCH):
            some = order[lo : lo + self.BATCH]
            length = int(lengths[some].max())
            at = np.minimum(starts[some][None, :] + np.arange(length)[:, None], len(data) - 1)
            inside = np.arange(length)[:, None] < lengths[some][None, :]
            steps = np.where(inside, data[at], np.uint8(PAD))
            both = np.concatenate([self._states(0, steps), self._states(1, steps)], axis=1)
            logits = np.matmul(self.out, both) + self.out_bias
            logits -= logits.max(1, keepdims=True)
            np.exp(logits, out=logits)
            logits *= (inside / logits.sum(1))[:, None, :]
            total[some] = logits.sum(0, dtype=np.float64).T
        return total


def _segment_kernel(settings: GruSettings):
    def run(batches):
        for batch in batches:
            lowered = pa.RecordBatch.from_arrays([*batch.columns[:2], pc.utf8_lower(batch.column(2))], names=["doc_id", "lang", "text"])
            for part, raw, borders in slices(lowered, "text"):
                data, rows = letter_stream(raw, borders)
                starts, lengths, ranges = cut_segments(rows, settings.segment)
                of = np.repeat(np.arange(part.num_rows), np.diff(ranges))
                found = [data[s : s + n].tobytes() for s, n in zip(starts, lengths, strict=True)]
                place = np.arange(len(of)) - ranges[of]
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(of)), part.column(1).take(pa.array(of)), pa.array(place.astype(np.int64)), pa.array(found, pa.binary())], names=["doc_id", "lang", "place", "segment"])

    return run


def training_segments(docs: DataFrame, settings: GruSettings) -> DataFrame:
    """(lang, segment) of the bounded training sample: documents with remainder <> 2 and a language.

    Each language has bounds of its own; documents and segments are chosen in a
    seeded hash order, ranked before anything is shuffled whole.
    """
    learn = docs.where((F.crc32(F.col("doc_id").cast("string")) % 4 != 2) & F.col("lang").isNotNull() & F.col("text").isNotNull())
    order = Window.partitionBy("lang").orderBy(F.xxhash64("doc_id", F.lit(settings.seed)), "doc_id")
    ids = learn.select("doc_id", "lang").distinct().withColumn("k", F.row_number().over(order)).where(F.col("k") <= settings.docs_per_language).select("doc_id", "lang")
    work = Workspace(docs.sparkSession, "language")
    ids = work.table("ids", ids)  # at most `docs_per_language` rows a language
    if ids.count() <= 500_000:
        ids = F.broadcast(ids)
    sample = learn.join(ids, ["doc_id", "lang"], "left_semi").select("doc_id", "lang", "text")
    cut = sample.mapInArrow(_segment_kernel(settings), "doc_id long, lang string, place long, segment binary")
    rank = Window.partitionBy("lang").orderBy(F.xxhash64("doc_id", "place", F.lit(settings.seed)), "segment")
    chosen = cut.withColumn("k", F.row_number().over(rank)).where(F.col("k") <= settings.segments)
    return chosen.select("lang", "segment").orderBy("lang", "segment")


def train(docs: DataFrame, settings: GruSettings = GruSettings()) -> LanguageModel | None:
    """A trained model; None if the sample holds no labelled letter."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    got = training_segments(rows, settings).toArrow().to_pydict()  # at most `segments` rows a language
    if not got["lang"]:
        return None
    languages = sorted(set(got["lang"]))
    labels = np.array([languages.index(x) for x in got["lang"]])
    mass = np.bincount(labels, minlength=len(languages))
    network = ByteGru(settings.hidden, len(languages), settings.seed)
    network.fit([bytes(x) for x in got["segment"]], labels, (len(labels) / len(languages) / mass[labels]).astype(np.float32), settings)
    return LanguageModel(network, languages, settings)


def _label_kernel(shared, text: int, names: list[str]):
    """Appends language and score to batches whose column ``text`` holds the text."""

    def run(batches):
        model: LanguageModel = shared.value
        labeller = SegmentLabeller(model.network)
        for batch in batches:
            lowered = pc.utf8_lower(batch.column(text))
            batch = pa.RecordBatch.from_arrays([*batch.columns, lowered], names=[*(str(k) for k in range(batch.num_columns)), "lowered"])
            for part, raw, borders in slices(batch, "lowered"):
                data, rows = letter_stream(raw, borders)
                starts, lengths, ranges = cut_segments(rows, model.settings.segment)
                filled = np.diff(rows) > 0
                probs = np.zeros((part.num_rows, len(model.languages)))
                if len(starts):
                    sums = labeller.sums(data, starts, lengths)
                    probs[filled] = np.add.reduceat(sums, ranges[:-1][filled], axis=0) / np.diff(rows)[filled][:, None]
                best = probs.argmax(1)
                lettered = filled.copy()
                plain = np.concatenate(([0], np.cumsum((raw >= 0x61) & (raw <= 0x7A))))[borders]
                for row in np.flatnonzero(filled & (np.diff(plain) == 0)):
                    lettered[row] = any(c.isalpha() for c in part.column(text)[row].as_py())
                found = [model.languages[b] if ok else "und" for b, ok in zip(best, lettered, strict=True)]
                scores = np.where(lettered, np.round(np.minimum(probs.max(1), 1.0), 6), 0.0)
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(found, pa.string()), pa.array(scores)], names=names)

    return run


def with_language(spark: SparkSession, docs: DataFrame, model: LanguageModel | None, lang: str, score: str) -> DataFrame:
    """All columns of ``docs`` and two more, of the given names, in one narrow pass."""
    if model is None:
        return docs.withColumns({lang: F.lit("und"), score: F.lit(0.0)})
    shared = spark.sparkContext.broadcast(model)  # 2 x 256 x 3 hidden floats, and as many outputs as languages
    names = [*docs.columns, lang, score]
    schema = T.StructType([*(T.StructField(f.name, f.dataType, True) for f in docs.schema), T.StructField(lang, T.StringType()), T.StructField(score, T.DoubleType())])
    return docs.mapInArrow(_label_kernel(shared, docs.columns.index("text"), names), schema)


def label_documents(spark: SparkSession, docs: DataFrame, model: LanguageModel | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document by a trained model.

    Null, empty or letter-free text is ``und`` with score 0 (so is everything if
    there was nothing to learn from); repeated rows get equal results, with or
    without doc_id (a null doc_id has a null ``held_out``); an empty table gives
    no rows; extra columns are ignored, whatever their names.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    labelled = with_language(spark, rows, model, "lang_pred", "score")
    return labelled.select("doc_id", (F.crc32(F.col("doc_id").cast("string")) % 4 == 2).alias("held_out"), "lang_pred", "score")


def identify_languages(spark: SparkSession, docs: DataFrame, settings: GruSettings = GruSettings()) -> DataFrame:
    """Train on the documents whose remainder is not 2, then label all."""
    return label_documents(spark, docs, train(docs, settings))


def fingerprint(model: LanguageModel) -> str:
    """Digest of the parameters, to show that training is deterministic."""
    return hashlib.sha256(b"".join(model.network.p[k].tobytes() for k in ByteGru.NAMES)).hexdigest()
