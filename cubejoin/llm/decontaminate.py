"""Benchmark decontamination as a prefix-filtered containment join.

An item contributes windows of ten consecutive words (an item with fewer words
is one window).  A window is a set of positioned shingles of five words, all of
which a document must hold at the right distances to contain it.  With a
containment threshold of one the necessary prefix is a single shingle, and the
global order by rarity (counted over all documents) makes it the rarest one:

1. one pass over the documents notes every place whose shingle may belong to a
   window (a Bloom filter of fixed size decides), with the words around it;
2. shingles are counted over these notes; a window that has an unseen shingle
   cannot occur and is dropped;
3. notes meet windows on the window's rarest shingle (salted join);
4. the offset of that shingle places the window, which must fit the document
   (positional and length bounds), and all its words are compared.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .textbatch import ALNUM, LOWER, Words, gram_hashes, slices
from .workspace import Workspace


@dataclass(frozen=True)
class WindowSettings:
    """window: words of a window; shingle: words of a join token; bloom_bits: log2 of the
    Bloom filter's bits (fixed size); salts: copies of a window's key in the join."""

    window: int = 10
    shingle: int = 5
    bloom_bits: int = 24
    salts: int = 16


def _window_kernel(settings: WindowSettings):
    def run(batches):
        for batch in batches:
            for part, raw, borders in slices(batch, "text"):
                low = LOWER[raw].tobytes()
                words = Words(raw, borders, ALNUM)
                out: list[tuple] = []
                ids = part.column(0).to_pylist()
                for row, item in enumerate(ids):
                    lo, hi = int(words.rows[row]), int(words.rows[row + 1])
                    if lo == hi:
                        continue
                    spelled = [low[words.starts[w] : words.ends[w]].decode() for w in range(lo, hi)]
                    size = min(settings.window, hi - lo)
                    gram = min(settings.shingle, size)
                    grams = gram_hashes(words.hashes[lo:hi], np.array([0, hi - lo]), gram)[0].view(np.int64).tolist()
                    kind = int.from_bytes(hashlib.blake2b(" ".join(spelled).encode(), digest_size=8).digest(), "little", signed=True)
                    for at in range(hi - lo - size + 1):
                        out.append((item, kind, " ".join(spelled[at : at + size]), size, gram, grams[at : at + size - gram + 1]))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(x, t) for x, t in zip(zip(*out) if out else [[]] * 6, (pa.string(), pa.int64(), pa.string(), pa.int32(), pa.int32(), pa.list_(pa.int64())), strict=True)],
                    names=["item_id", "kind", "window", "size", "gram", "grams"],
                )

    return run


def _bloom_places(hashes: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    down = np.uint64(64 - bits)
    return (hashes >> down).astype(np.int64), ((hashes * np.uint64(0xC2B2AE3D27D4EB4F)) >> down).astype(np.int64)


def _bloom_kernel(settings: WindowSettings):
    def run(batches):
        for batch in batches:
            hashes = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            places = np.unique(np.concatenate(_bloom_places(hashes, settings.bloom_bits)))
            yield pa.RecordBatch.from_arrays([pa.array(places >> 6), pa.array(np.int64(1) << (places & 63))], names=["word", "bits"])

    return run


def _note_kernel(settings: WindowSettings, bloom, sizes: list[int]):
    def run(batches):
        filled = np.unpackbits(np.frombuffer(bloom.value, np.uint8), bitorder="little").view(bool)
        reach = settings.window
        for batch in batches:
            for part, raw, borders in slices(batch, "text"):
                words = Words(raw, borders, ALNUM)
                low = LOWER[raw].tobytes()
                counts = np.diff(words.rows)
                ids, keys = part.column(0), part.column(1)
                yield pa.RecordBatch.from_arrays(
                    [ids, keys, pa.array(counts), pa.nulls(len(ids), pa.int64()), pa.nulls(len(ids), pa.int32()), pa.nulls(len(ids), pa.int32()), pa.nulls(len(ids), pa.string())],
                    names=["doc_id", "text_key", "n_words", "token", "place", "first", "around"],
                )
                for size in sizes:
                    grams, at, rows = gram_hashes(words.hashes, words.rows, size)
                    if not len(grams):
                        continue
                    one, two = _bloom_places(grams, settings.bloom_bits)
                    hits = np.flatnonzero(filled[one])
                    hits = hits[filled[two[hits]]]
                    for lo in range(0, len(hits), 20000):
                        some = hits[lo : lo + 20000]
                        row = np.searchsorted(rows, some, "right") - 1
                        head, tail = words.rows[row], words.rows[row + 1]
                        first = np.maximum(head, at[some] - (reach - size))
                        last = np.minimum(tail, at[some] + reach)
                        spans = zip(first.tolist(), last.tolist(), strict=True)
                        starts, ends = words.starts, words.ends
                        around = [b" ".join([low[starts[w] : ends[w]] for w in range(f, e)]).decode() for f, e in spans]
                        yield pa.RecordBatch.from_arrays(
                            [ids.take(pa.array(row)), keys.take(pa.array(row)), pa.nulls(len(some), pa.int64()), pa.array(grams[some].view(np.int64)), pa.array((at[some] - head).astype(np.int32)), pa.array((first - head).astype(np.int32)), pa.array(around)],
                            names=["doc_id", "text_key", "n_words", "token", "place", "first", "around"],
                        )

    return run


def contamination(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, settings: WindowSettings = WindowSettings()) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated, text_key.

    * null or word-free text: no words, no hits;
    * items without words or without item_id have no windows;
    * equal items each count;
    * rows are told apart by doc_id and text (``text_key`` is the text's hash), so
      rows of one doc_id or without doc_id get the hits of their own text, and
      rows equal in both get equal results;
    * empty tables: no rows, or rows without hits; extra columns are ignored,
      whatever their names.
    """
    work = Workspace(spark, "contamination")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    docs = docs.select("doc_id", F.xxhash64("text").alias("text_key"), "text")
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null")
    raw = work.table("raw_windows", items.mapInArrow(_window_kernel(settings), "item_id string, kind long, window string, size int, gram int, grams array<long>"))
    windows = raw.groupBy("window").agg(F.first("size").alias("size"), F.first("gram").alias("gram"), F.first("grams").alias("grams"), F.collect_set("kind").alias("kinds"))
    windows = work.table("windows", windows)

    tokens = windows.select(F.explode("grams").alias("token")).distinct()
    bits = tokens.mapInArrow(_bloom_kernel(settings), "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()
    table = np.zeros((1 << settings.bloom_bits) >> 6, np.int64)  # fixed size
    table[bits.column("word").to_numpy()] = bits.column("bits").to_numpy()
    sizes = sorted(r.gram for r in windows.select("gram").distinct().collect())  # at most `shingle` values
    bloom = spark.sparkContext.broadcast(table.tobytes())
    schema = "doc_id long, text_key long, n_words long, token long, place int, first int, around string"
    notes = work.table("notes", docs.mapInArrow(_note_kernel(settings, bloom, sizes), schema))
    hits = notes.where("token is not null")

    seen = hits.groupBy("token").agg(F.count("*").alias("often"))
    placed = windows.select("window", "size", "kinds", F.size("grams").alias("needed"), F.posexplode("grams").alias("offset", "token"))
    rated = placed.join(seen, "token")
    keys = rated.groupBy("window").agg(F.first("size").alias("size"), F.first("kinds").alias("kinds"), F.first("needed").alias("needed"), F.count("*").alias("found"), F.min(F.struct("often", "token", "offset")).alias("rare"))
    keys = keys.where("found = needed").select("window", "size", "kinds", F.col("rare.token").alias("token"), F.col("rare.offset").alias("offset"))
    keys = keys.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(settings.salts - 1))))
    salted = hits.withColumn("salt", F.pmod(F.xxhash64("doc_id", "text_key", "place"), F.lit(settings.salts)).cast("int"))
    start = F.col("place") - F.col("offset")
    inside = F.slice(F.split("around", " "), F.greatest(start - F.col("first") + 1, F.lit(1)), F.col("size"))
    found = salted.join(keys, ["token", "salt"]).where((start >= F.col("first")) & (F.concat_ws(" ", inside) == F.col("window")))
    spans = found.select("doc_id", "text_key", start.alias("start"), "size", "kinds")

    covered = F.aggregate(
        F.sort_array(F.collect_set(F.struct("start", "size"))),
        F.struct(F.lit(0).cast("long").alias("hit"), F.lit(0).alias("end")),
        lambda acc, s: F.struct(
            (acc["hit"] + F.greatest(s["start"] + s["size"] - F.greatest(acc["end"], s["start"]), F.lit(0))).cast("long").alias("hit"),
            F.greatest(acc["end"], s["start"] + s["size"]).alias("end"),
        ),
        lambda acc: acc["hit"],
    )
    spans = work.table("spans", spans)
    row = ["doc_id", "text_key"]
    per_doc = spans.groupBy(*row).agg(covered.alias("n_hit"))
    kinds = raw.select("kind", "item_id").distinct()
    named = spans.select(*row, F.explode("kinds").alias("kind")).distinct().join(kinds, "kind")
    named = named.groupBy(*row).agg(F.sort_array(F.collect_set("item_id")).alias("ids")).select(F.col("doc_id").alias("named_id"), F.col("text_key").alias("named_key"), "ids")
    found = per_doc.join(named, F.col("doc_id").eqNullSafe(F.col("named_id")) & (F.col("text_key") == F.col("named_key")), "left")
    found = found.select(F.col("doc_id").alias("hit_id"), F.col("text_key").alias("hit_key"), "n_hit", "ids")
    rows = notes.where("n_words is not null").select(*row, "n_words")
    joined = rows.join(found, F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("text_key") == F.col("hit_key")), "left")
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    ids = F.coalesce("ids", F.array().cast("array<string>"))
    result = joined.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size(ids).cast("long").alias("n_items"), F.sha2(F.concat_ws(",", ids), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"), "text_key")
    result = work.table("result", result)
    work.keep("result")
    return result
