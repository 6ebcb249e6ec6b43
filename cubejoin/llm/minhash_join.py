"""Near-duplicate join over MinHash signature coordinates.

Documents are sets of distinct five-word shingles.  A signature keeps, for each
of ``coordinates`` keyed permutations, the smallest image of the set; two sets
agree in a coordinate with probability equal to their Jaccard similarity.  The
signature is then treated as a set of (coordinate, value) tokens and joined
with itself through an inverted index:

*prefix*: tokens are put in one global order, rare ones first.  Two signatures
that share at least ``match`` of ``coordinates`` tokens share one within their
first ``coordinates - match + 1``, so only those are posted.

*skip*: a posting list first joins its members to one pivot (its most typical
member); of its pivots a member tries the ``tries`` it collides with most.  Members
which fall into the pivot's component need no further comparison with each
other; only the others meet the rest of the list, and a one-bit sketch drops
most of these meetings inside the join.  In lists of more than ``direct``
members the others meet through the exact shingle sets instead: each set's
rarest shingles (the necessary prefix of its Jaccard bound) are posted, a shared
shingle counts only where its positions leave room for the overlap that a link
needs and the sets' parities (the sum modulo 2 of the images of a set in
``PARITY_BITS`` places, of which two sets differ in no more places than they have
shingles apart) do not exclude it, and long lists meet in parts of ``part``
members, each a task of its own.  Both bounds are exact and act inside the join.
No list is cut short and no group emits all pairs.  ``tries``, ``direct`` and ``part``
decide where the work is done, never which links are found.

*count*: a candidate pair is kept if its signatures agree in at least ``match``
coordinates, and becomes a link only if the exact shingle sets say so.

The default threshold pair (64 coordinates, 36 matches) misses a pair of
similarity 0.85 with probability about 1e-8, and the 1-bit sketch about 1e-7;
``JoinSettings.for_similarity`` keeps these odds at other thresholds.

Equal sets are one vertex of the graph of links (their 128-bit digests are
equal), whichever rows they come from.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass
from functools import reduce
from math import ceil, sqrt
from operator import add

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import connected_components
from .textbatch import NON_BLANK, Words, gram_hashes, mix, slices
from .workspace import Workspace, small_batches

SHINGLE_WORDS = 5
#: Fixed value: places of a set's parity, a multiple of 64.
PARITY_BITS = 1024


@dataclass(frozen=True)
class JoinSettings:
    """Production parameters.

    similarity_percent: links have 100 * |A n B| >= this * |A u B|.
    coordinates / match: signature length and the collisions that make a candidate.
    sketch_distance: largest Hamming distance of the 64 one-bit sketches of a candidate.
    bucket_bits: size (2**bits counters, fixed) of the frequency sketches.
    tries: pivots that a member is compared with before lists meet; the rest meets all the same.
    direct: posting lists up to this length compare their stray members directly.
    part: members of a part of a long list of set tokens.
    """

    similarity_percent: int = 85
    coordinates: int = 64
    match: int = 36
    sketch_distance: int = 18
    bucket_bits: int = 20
    tries: int = 3
    direct: int = 16
    part: int = 512
    seed: int = 7

    @classmethod
    def for_similarity(cls, percent: int, coordinates: int = 64, deviations: float = 5.8) -> JoinSettings:
        """Collisions and sketch bits so many standard deviations off what a pair at the threshold has."""
        s = percent / 100
        match = int(coordinates * s - deviations * sqrt(coordinates * s * (1 - s)))
        flip = (1 - s) / 2
        distance = ceil(coordinates * flip + deviations * sqrt(coordinates * flip * (1 - flip)))
        return cls(similarity_percent=percent, coordinates=coordinates, match=max(1, match), sketch_distance=min(coordinates, distance))

    @property
    def prefix(self) -> int:
        return self.coordinates - self.match + 1


def shingle_sets(batch_slice, raw, borders) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each row, concatenated, and their row borders."""
    words = Words(raw, borders, NON_BLANK)
    grams, _, gram_rows = gram_hashes(words.hashes, words.rows, SHINGLE_WORDS)
    sets: list[np.ndarray] = []
    n_words = np.diff(words.rows)
    for row in range(len(n_words)):
        if n_words[row] >= SHINGLE_WORDS:
            values = np.sort(grams[gram_rows[row] : gram_rows[row + 1]])
            keep = np.empty(len(values), bool)
            keep[0] = True
            np.not_equal(values[1:], values[:-1], out=keep[1:])
            sets.append(values[keep])
        elif n_words[row]:
            short = words.hashes[words.rows[row] : words.rows[row + 1]]
            sets.append(gram_hashes(short, np.array([0, len(short)]), len(short))[0])
        else:
            sets.append(np.empty(0, np.uint64))
    sizes = np.array([len(s) for s in sets], dtype=np.int64)
    return (np.concatenate(sets) if sets else np.empty(0, np.uint64)), np.concatenate(([0], np.cumsum(sizes)))


def _permutations(settings: JoinSettings) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.Generator(np.random.PCG64(settings.seed))
    flips = rng.integers(0, 2**32, settings.coordinates, dtype=np.uint32)
    factors = rng.integers(0, 2**31, settings.coordinates, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
    return flips, factors


def _signature_kernel(settings: JoinSettings):
    def run(batches):
        flips, factors = _permutations(settings)
        for batch in batches:
            for part, raw, borders in slices(batch, "text"):
                values, rows = shingle_sets(part, raw, borders)
                sizes = np.diff(rows)
                full = sizes > 0
                heads = rows[:-1][full]
                digests = np.zeros((len(sizes), 2), np.int64)
                for row in np.flatnonzero(full):
                    own = hashlib.blake2b(values[rows[row] : rows[row + 1]], digest_size=16).digest()
                    digests[row] = np.frombuffer(own, "<i8")
                signature = np.zeros((len(sizes), settings.coordinates), np.uint32)
                if len(values):
                    narrow = (values >> np.uint64(32)).astype(np.uint32)
                    image = np.empty_like(narrow)
                    for k in range(settings.coordinates):
                        np.bitwise_xor(narrow, flips[k], out=image)
                        np.multiply(image, factors[k], out=image)
                        signature[full, k] = np.minimum.reduceat(image, heads)
                flat = pa.array(signature.view(np.int32).ravel())
                ends = pa.array(np.arange(len(sizes) + 1, dtype=np.int32) * settings.coordinates)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(1), pa.array(sizes), pa.array(digests[:, 0]), pa.array(digests[:, 1]), pa.ListArray.from_arrays(ends, flat)],
                    names=["doc_id", "text_key", "n_shingles", "low", "high", "signature"],
                )

    return run


def _token_matrix(batch, settings: JoinSettings) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of a batch of signatures and their counter in the frequency sketch."""
    flat = batch.column(batch.schema.get_field_index("signature")).flatten().to_numpy(zero_copy_only=False)
    values = flat.view(np.uint32).reshape(-1, settings.coordinates).astype(np.uint64)
    tokens = mix(values | (np.arange(1, settings.coordinates + 1, dtype=np.uint64) << np.uint64(32)))
    return tokens, (tokens >> np.uint64(64 - settings.bucket_bits)).astype(np.int64)


def _frequency_kernel(settings: JoinSettings):
    def run(batches):
        counts = np.zeros(1 << settings.bucket_bits, np.int64)
        for batch in batches:
            if batch.num_rows:
                counts += np.bincount(_token_matrix(batch, settings)[1].ravel(), minlength=len(counts))
        used = np.flatnonzero(counts)
        for lo in range(0, len(used), 1 << 16):
            at = used[lo : lo + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(counts[at])], names=["bucket", "n"])

    return run


def _posting_kernel(settings: JoinSettings, frequencies):
    """Rows (class_id, n_shingles, root, signature) to (token, id, n, root, sketch, typical)."""

    def run(batches):
        table = np.frombuffer(frequencies.value, dtype=np.int64)
        for batch in batches:
            for lo in range(0, batch.num_rows, 4096):
                part = batch.slice(lo, 4096)
                tokens, buckets = _token_matrix(part, settings)
                counts = table[buckets]
                order = np.lexsort((tokens, counts), axis=1)[:, : settings.prefix]
                chosen = np.take_along_axis(tokens, order, axis=1)
                bits = ((tokens >> np.uint64(1)) & np.uint64(1)) << np.arange(settings.coordinates, dtype=np.uint64)
                sketch = np.bitwise_or.reduce(bits, axis=1)
                typical = np.minimum(counts, 1 << 40).sum(axis=1)
                rep = lambda x: pa.array(np.repeat(x, settings.prefix))
                ids, sizes, roots = (part.column(k).to_numpy() for k in range(3))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(chosen.view(np.int64).ravel()), rep(ids), rep(sizes), rep(roots), rep(sketch.view(np.int64)), rep(typical)],
                    names=["token", "id", "n", "root", "sketch", "typical"],
                )

    return run


def _brief_kernel(settings: JoinSettings):
    """One byte of each coordinate: enough to count collisions (a strict count never exceeds it)."""

    def run(batches):
        for batch in batches:
            flat = batch.column(1).flatten().to_numpy(zero_copy_only=False)
            mixed = ((flat.view(np.uint32).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(56)).astype(np.uint8).view(np.int8)
            ends = pa.array(np.arange(batch.num_rows + 1, dtype=np.int32) * settings.coordinates)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(ends, pa.array(mixed))], names=["id", "brief"])

    return run


def _set_kernel(text: str):
    def run(batches):
        for batch in batches:
            for part, raw, borders in slices(batch, text):
                values, rows = shingle_sets(part, raw, borders)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.ListArray.from_arrays(pa.array(rows.astype(np.int32)), pa.array(values.view(np.int64)))],
                    names=["id", "shingles"],
                )

    return run


def _set_rows(batch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    lists = batch.column(batch.schema.get_field_index("shingles"))
    ends = lists.offsets.to_numpy()
    values = lists.values.to_numpy(zero_copy_only=False).view(np.uint64)
    return batch.column(batch.schema.get_field_index("id")).to_numpy(), ends, values


def _set_frequency_kernel(settings: JoinSettings):
    def run(batches):
        counts = np.zeros(1 << settings.bucket_bits, np.int64)
        down = np.uint64(64 - settings.bucket_bits)
        for batch in batches:
            if batch.num_rows:
                _, ends, values = _set_rows(batch)
                counts += np.bincount((values[ends[0] : ends[-1]] >> down).astype(np.int64), minlength=len(counts))
        used = np.flatnonzero(counts)
        for lo in range(0, len(used), 1 << 16):
            at = used[lo : lo + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(counts[at])], names=["bucket", "n"])

    return run


def _set_prefix_kernel(settings: JoinSettings, frequencies):
    def run(batches):
        table = np.frombuffer(frequencies.value, dtype=np.int64)
        down = np.uint64(64 - settings.bucket_bits)
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, ends, values = _set_rows(batch)
            for row in range(batch.num_rows):
                own = values[ends[row] : ends[row + 1]]
                n = len(own)
                need = -(-settings.similarity_percent * n // 100)
                order = np.lexsort((own, table[(own >> down).astype(np.int64)]))[: n - need + 1]
                k = len(order)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(own[order].view(np.int64)), pa.array(np.full(k, ids[row])), pa.array(np.arange(k, dtype=np.int32)), pa.array(np.full(k, n, np.int64))],
                    names=["token", "id", "rank", "n"],
                )

    return run


def _parity_kernel(batches):
    """(id, one long for each 64 places) of sets."""
    words = PARITY_BITS // 64
    for batch in batches:
        ids, ends, values = _set_rows(batch)
        places = (values & np.uint64(PARITY_BITS - 1)).astype(np.int64)
        parities = np.zeros((len(ids), words), np.int64)
        for row in range(len(ids)):
            odd = np.bincount(places[ends[row] : ends[row + 1]], minlength=PARITY_BITS) & 1
            parities[row] = np.packbits(odd.astype(np.uint8)).view(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(ids), *(pa.array(parities[:, k].copy()) for k in range(words))], names=["id", *(f"p{k}" for k in range(words))])


def _sketch(spark: SparkSession, counted: DataFrame, settings: JoinSettings):
    """Broadcast counters of a (bucket, n) frame: a fixed size, whatever the corpus."""
    with small_batches(spark):
        got = counted.groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    table = np.zeros(1 << settings.bucket_bits, np.int64)
    table[got.column("bucket").to_numpy()] = got.column("n").to_numpy()
    return spark.sparkContext.broadcast(table.tobytes())


def identified(docs: DataFrame) -> DataFrame:
    """doc_id, text and text_key: together doc_id and text_key tell rows apart, null ids included."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.select("doc_id", F.xxhash64("text").alias("text_key"), "text")


def _sets_of(docs: DataFrame, classes: DataFrame, wanted: DataFrame) -> DataFrame:
    """Exact shingle sets of the classes whose id is in ``wanted`` (class_id, distinct), from their leaders' texts."""
    leaders = classes.select("class_id", F.col("lead").alias("lead_id"), F.col("lead_key")).join(wanted, "class_id", "left_semi")
    texts = docs.join(leaders.hint("shuffle_hash"), F.col("doc_id").eqNullSafe(F.col("lead_id")) & (F.col("text_key") == F.col("lead_key")))
    sets = texts.select("class_id", "text").mapInArrow(_set_kernel("text"), "id long, shingles array<long>")
    return sets.dropDuplicates(["id"])  # equal rows may lead one class


def _set_prefix_pairs(work: Workspace, sets: DataFrame, roots: DataFrame, settings: JoinSettings) -> DataFrame:
    """Pairs (a, b) of different roots which the exact prefix, position and parity bounds cannot exclude."""
    spark = work.spark
    frequencies = _sketch(spark, sets.mapInArrow(_set_frequency_kernel(settings), "bucket int, n long"), settings)
    rows = sets.mapInArrow(_set_prefix_kernel(settings, frequencies), "token long, id long, rank int, n long")
    rows = work.table("prefix_rows", rows.join(roots, "id", "left").withColumn("root", F.coalesce("root", "id")))
    held = rows.groupBy("token", "root").agg(F.count("*").alias("c"))
    major = held.groupBy("token").agg(F.max(F.struct("c", "root")).alias("m"), F.count("*").alias("roots"), F.sum("c").alias("members")).where("roots > 1")
    parts = F.ceil(F.col("members") / settings.part).cast("int")
    major = work.table("majors", major.select("token", F.col("m.root").alias("major"), parts.alias("parts")))
    words = [f"p{k}" for k in range(PARITY_BITS // 64)]
    parities = sets.mapInArrow(_parity_kernel, f"id long, {', '.join(f'{w} long' for w in words)}")
    marked = work.table("marked_rows", rows.join(major, "token").join(parities, "id"))
    stray = marked.where("root <> major").select("token", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.col("id").alias("sid"), F.col("n").alias("sn"), F.col("rank").alias("srank"), F.col("root").alias("sroot"), *(F.col(w).alias(f"s{w}") for w in words))
    marked = marked.withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int"))
    p = settings.similarity_percent
    room = F.least(F.col("n") - F.col("rank"), F.col("sn") - F.col("srank"))  # the shared shingle and all after it
    fits = (100 + p) * room >= p * (F.col("n") + F.col("sn"))
    sized = 100 * F.least("n", "sn") >= p * F.greatest("n", "sn")
    apart = reduce(add, (F.bit_count(F.col(w).bitwiseXOR(F.col(f"s{w}"))) for w in words))  # no more than the shingles in one set only
    near = (100 + p) * apart <= (100 - p) * (F.col("n") + F.col("sn"))
    meets = (F.col("sroot") != F.col("root")) & ((F.col("root") == F.col("major")) | (F.col("sid") < F.col("id"))) & sized & fits & near
    return marked.join(stray, ["token", "part"]).where(meets).select(F.least("id", "sid").alias("a"), F.greatest("id", "sid").alias("b")).distinct()


def _confirm(work: Workspace, label: str, docs: DataFrame, classes: DataFrame, briefs: DataFrame, pairs: DataFrame, settings: JoinSettings) -> DataFrame:
    """Links among candidate pairs (a, b): collision count, then exact sets."""
    one = briefs.select(F.col("id").alias("a"), F.col("brief").alias("sa"))
    two = briefs.select(F.col("id").alias("b"), F.col("brief").alias("sb"))
    equal = F.aggregate(F.zip_with("sa", "sb", lambda x, y: F.when(x == y, 1).otherwise(0)), F.lit(0), lambda s, x: s + x)
    candidates = work.table(f"{label}_candidates", pairs.join(one, "a").join(two, "b").where(equal >= settings.match).select("a", "b"))
    wanted = candidates.select(F.explode(F.array("a", "b")).alias("class_id")).distinct()
    sets = work.table(f"{label}_sets", _sets_of(docs, classes, wanted))
    left = sets.select(F.col("id").alias("a"), F.col("shingles").alias("la"))
    right = sets.select(F.col("id").alias("b"), F.col("shingles").alias("lb"))
    common = F.size(F.array_intersect("la", "lb"))
    both = F.size("la") + F.size("lb")
    joined = candidates.join(left, "a").join(right, "b")
    links = work.table(f"{label}_links", joined.where(100 * common >= settings.similarity_percent * (both - common)).select("a", "b"))
    work.drop(f"{label}_sets")
    return links


def near_duplicates(spark: SparkSession, docs: DataFrame, settings: JoinSettings = JoinSettings()) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept, text_key, group_id.

    * null, empty or blank text: no shingles, its own component (component_id is
      its doc_id), kept, no group_id;
    * fewer than five words: the whole word sequence is the one shingle;
    * every row is a document of its own: rows of one doc_id with different texts
      link through their own texts (``text_key`` is the text's hash), equal rows
      get equal results, and a shared doc_id alone links nothing;
    * rows without doc_id link as others do; ``component_id`` is the smallest
      doc_id of the component, null where none has one, and ``kept`` is true where
      doc_id and component_id are equal or both null;
    * ``group_id`` names the component, with or without ids, within this result;
    * empty tables give an empty result; other columns are ignored, whatever
      their names.
    """
    work = Workspace(spark, "near_duplicates")
    docs = identified(docs)
    schema = "doc_id long, text_key long, n_shingles long, low long, high long, signature array<int>"
    signatures = work.table("signatures", docs.mapInArrow(_signature_kernel(settings), schema))

    key = ["n_shingles", "low", "high"]
    leader = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_key", "signature")).alias("m")
    classes = signatures.where("n_shingles > 0").groupBy(*key).agg(leader)
    # Numbers are drawn once: the table is written before anything reads them.
    classes = work.table("classes", classes.select(F.monotonically_increasing_id().alias("class_id"), *key, F.col("m.doc_id").alias("lead"), F.col("m.text_key").alias("lead_key"), F.col("m.signature").alias("signature")))
    briefs = work.table("briefs", classes.select("class_id", "signature").mapInArrow(_brief_kernel(settings), "id long, brief array<byte>"))

    frequencies = _sketch(spark, classes.select("signature").mapInArrow(_frequency_kernel(settings), "bucket int, n long"), settings)

    def postings(of: DataFrame) -> DataFrame:
        return of.select("class_id", "n_shingles", "root", "signature").mapInArrow(_posting_kernel(settings, frequencies), "token long, id long, n long, root long, sketch long, typical long")

    alike = lambda s, t, n, m: (F.bit_count(F.col(s).bitwiseXOR(F.col(t))) <= settings.sketch_distance) & (100 * F.least(n, m) >= settings.similarity_percent * F.greatest(n, m))
    posted = postings(classes.withColumn("root", F.col("class_id")))
    pivots = posted.groupBy("token").agg(F.max(F.struct("typical", "id", "n", "sketch")).alias("p"), F.count("*").alias("held")).where("held > 1")
    pivots = work.table("pivots", pivots.select("token", F.col("p.id").alias("pivot"), F.col("p.n").alias("pivot_n"), F.col("p.sketch").alias("pivot_sketch"), "held"))
    stars = posted.select("token", "id", "n", "sketch").join(pivots, "token").where((F.col("id") != F.col("pivot")) & alike("sketch", "pivot_sketch", "n", "pivot_n"))
    # An id has at most one pivot for each posted coordinate.
    tried = stars.groupBy("id", "pivot").agg(F.count("*").alias("c")).groupBy("id").agg(F.sort_array(F.collect_list(F.struct("c", "pivot")), asc=False).alias("m"))
    best = tried.select("id", F.explode(F.slice("m", 1, settings.tries)).alias("m"))
    stars = work.table("stars", best.select(F.least("id", "m.pivot").alias("a"), F.greatest("id", "m.pivot").alias("b")).distinct())
    first = _confirm(work, "first", docs, classes, briefs, stars, settings)
    grouped = connected_components(work, first, "first_cc")

    root = grouped.select(F.col("node").alias("class_id"), "root")
    placed = postings(classes.join(root, "class_id", "left").withColumn("root", F.coalesce("root", "class_id"))).drop("typical")
    mixed = placed.groupBy("token").agg(F.min("root").alias("r"), F.max("root").alias("s")).where("r <> s").select("token")
    tokens = mixed.join(pivots, "token").join(root.select(F.col("class_id").alias("pivot"), F.col("root").alias("pivot_root")), "pivot", "left")
    tokens = work.table("tokens", tokens.select("token", "held", F.coalesce("pivot_root", "pivot").alias("pivot_root")))
    placed = work.table("placed", placed.join(tokens, "token"))
    short = placed.where(F.col("held") <= settings.direct)
    stray = short.where("root <> pivot_root").select("token", F.col("id").alias("sid"), F.col("n").alias("sn"), F.col("sketch").alias("ss"), F.col("root").alias("sroot"))
    meets = (F.col("sroot") != F.col("root")) & ((F.col("root") == F.col("pivot_root")) | (F.col("sid") < F.col("id"))) & alike("sketch", "ss", "n", "sn")
    few = short.join(stray, "token").where(meets).select(F.least("id", "sid").alias("a"), F.greatest("id", "sid").alias("b")).distinct()
    crowd = placed.where(F.col("held") > settings.direct).select(F.col("id").alias("class_id")).distinct()
    crowd_sets = work.table("crowd_sets", _sets_of(docs, classes, crowd))
    many = _set_prefix_pairs(work, crowd_sets, root.withColumnRenamed("class_id", "id"), settings)
    rest = work.table("rest", few.union(many).distinct().join(stars, ["a", "b"], "left_anti"))
    work.drop("crowd_sets", "placed", "pivots", "tokens", "prefix_rows", "marked_rows")
    second = _confirm(work, "second", docs, classes, briefs, rest, settings)

    # The first components are single vertices of what the second links join.
    ends = second.join(root.select(F.col("class_id").alias("a"), F.col("root").alias("ra")), "a", "left").join(root.select(F.col("class_id").alias("b"), F.col("root").alias("rb")), "b", "left")
    final = connected_components(work, ends.select(F.coalesce("ra", "a").alias("a"), F.coalesce("rb", "b").alias("b")), "final_cc")
    joined = classes.select("class_id", *key, "lead").join(root, "class_id", "left").withColumn("first_id", F.coalesce("root", "class_id")).drop("root")
    joined = joined.join(final.select(F.col("node").alias("first_id"), "root"), "first_id", "left").withColumn("group_id", F.coalesce("root", "first_id"))
    joined = work.table("joined", joined.select(*key, "lead", "group_id"))
    named = joined.groupBy("group_id").agg(F.min("lead").alias("component_id"))
    placed_classes = work.table("placed_classes", joined.drop("lead").join(named, "group_id"))
    result = signatures.select("doc_id", "text_key", *key).join(placed_classes, key, "left")
    component = F.when(F.col("n_shingles") == 0, F.col("doc_id")).otherwise(F.col("component_id"))
    result = work.table("result", result.select("doc_id", "n_shingles", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"), "text_key", "group_id"))
    work.keep("result")
    return result
