"""Nearest neighbours by shifted space-filling curves.

Vectors are projected to few dimensions (seeded orthogonal projections), shifted
by a random offset and ordered along a Hilbert curve; several such orderings are
range-partitioned by Spark and cut into windows of ``block`` consecutive keys.  A
query meets its own window and ``reach`` neighbouring ones on either side in
every ordering; the meetings merge and are reranked by exact inner products.

Where vectors have structure, the windows find most neighbours.  Where they have
none (in 64 independent dimensions neighbours are barely nearer than strangers),
no small windows can reach the required recall, so with ``expand`` they are
widened by proof: stretches of ``ball`` consecutive keys of the first ordering
keep their centre and radius, and a query also visits each stretch whose bound
<q, centre> + |q| * radius reaches the score of its k-th find so far.  The result
is then the exact one.  Stretches travel by shelves of ``shelf``: a query is sent
to a shelf once, however many of its stretches it visits, and takes its best
finds home together.  Queries and vectors meet block by block, in bounded
pieces; no side of a join that grows with the vectors is broadcast.  Vectors of different lengths have no inner product: each length is
ordered and searched by itself.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .workspace import Workspace


@dataclass(frozen=True)
class CurveSettings:
    """k: neighbours; orderings, dimensions, bits: the curves; block: vectors of a window; reach:
    neighbouring windows on either side; expand: widen by bounds until exact, over stretches of
    ``ball`` vectors, ``shelf`` stretches together; query_block: queries of a piece; partitions: of the range partitioning (None:
    the session's)."""

    k: int = 20
    orderings: int = 6
    dimensions: int = 8
    bits: int = 7
    block: int = 128
    reach: int = 2
    ball: int = 1024
    shelf: int = 8
    query_block: int = 1024
    partitions: int | None = None
    expand: bool = True
    seed: int = 17


def hilbert_keys(cells: np.ndarray, bits: int) -> np.ndarray:
    """Hilbert index of integer points (rows), by the transpose method, vectorised; bits * columns <= 63."""
    x = cells.astype(np.int64).T.copy()
    n = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(n):
            high = (x[i] & q) != 0
            swap = np.where(high, 0, (x[0] ^ x[i]) & p)
            x[0] = np.where(high, x[0] ^ p, x[0] ^ swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, n):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        t = np.where(x[n - 1] & q, t ^ (q - 1), t)
        q >>= 1
    x ^= t
    key = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(n):
            key = (key << 1) | ((x[i] >> b) & 1)
    return key


def _matrix(column: pa.Array) -> np.ndarray:
    """Rows of equal length as doubles."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1)


def _key_kernel(settings: CurveSettings):
    """Rows (vec_id, v, d, reach) to (vec_id, d, ordering, key)."""

    def run(batches):
        plans: dict[int, list] = {}
        for batch in batches:
            lengths = batch.column(2).to_numpy()
            for d in np.unique(lengths):
                part = batch.filter(pa.array(lengths == d))
                if d not in plans:
                    rng = np.random.Generator(np.random.PCG64([settings.seed, int(d)]))
                    bases = [np.linalg.qr(rng.standard_normal((d, d)))[0][:, : min(settings.dimensions, d)] for _ in range(settings.orderings)]
                    plans[d] = [(basis, rng.random(basis.shape[1]) * 0.5) for basis in bases]
                reach = part.column(3).to_numpy()[:, None]
                vectors = _matrix(part.column(1)) / reach  # components in [-1, 1]
                for ordering, (basis, shift) in enumerate(plans[d]):
                    place = (vectors @ basis * (d**0.5 / 6) + 0.5) * 0.5 + shift
                    cells = np.clip(place * (1 << settings.bits), 0, (1 << settings.bits) - 1).astype(np.int64)
                    yield pa.RecordBatch.from_arrays(
                        [part.column(0), part.column(2), pa.array(np.full(part.num_rows, ordering, np.int32)), pa.array(hilbert_keys(cells, settings.bits))],
                        names=["vec_id", "d", "ordering", "key"],
                    )

    return run


def exact_scores(q: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Inner products of paired rows, summed component by component from the first on."""
    with np.errstate(over="ignore", invalid="ignore"):
        total = np.zeros(len(q))
        for j in range(q.shape[1]):
            total += q[:, j] * v[:, j]
    return np.where(np.isnan(total), -np.inf, total)  # infinities of both signs


def best_pairs(q_ids: np.ndarray, q: np.ndarray, floors: np.ndarray, v_ids: np.ndarray, v: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, vector, exact score) of the k nearest of each query that reach its floor; ties to smaller ids.

    Matrix products choose with a margin for their rounding, exact sums decide.
    """
    with np.errstate(over="ignore", invalid="ignore"):
        rough = np.nan_to_num(q @ v.T, nan=-np.inf)
        slack = 4e-16 * q.shape[1] * np.sqrt((q * q).sum(1)) * np.sqrt((v * v).sum(1).max())
    slack = np.where(np.isfinite(slack), slack, np.inf)
    rough[q_ids[:, None] == v_ids[None, :]] = -np.inf
    floor = floors.copy()
    if rough.shape[1] > k:
        floor = np.maximum(floor, np.partition(rough, -k, axis=1)[:, -k])
    with np.errstate(invalid="ignore"):
        least = np.where(np.isfinite(floor) & np.isfinite(slack), floor - 2 * slack, -np.inf)
    some_q, some_v = np.nonzero((rough >= least[:, None]) & (q_ids[:, None] != v_ids[None, :]))
    scores = np.empty(len(some_q))
    for lo in range(0, len(some_q), 1 << 16):
        cut = slice(lo, lo + (1 << 16))
        scores[cut] = exact_scores(q[some_q[cut]], v[some_v[cut]])
    order = np.lexsort((v_ids[some_v], -scores, some_q))
    some_q, some_v, scores = some_q[order], some_v[order], scores[order]
    heads = np.searchsorted(some_q, np.arange(len(q_ids)))
    keep = (np.arange(len(some_q)) - heads[some_q] < k) & (scores >= floors[some_q])
    return q_ids[some_q[keep]], v_ids[some_v[keep]], scores[keep]


def _meet_kernel(settings: CurveSettings):
    def run(batches):
        for batch in batches:
            for row in range(batch.num_rows):
                queries, vectors = batch.column(0)[row].values, batch.column(1)[row].values
                floors = queries.field(2).to_numpy(zero_copy_only=False)
                found = best_pairs(queries.field(0).to_numpy(), _matrix(queries.field(1)), np.where(np.isnan(floors), -np.inf, floors), vectors.field(0).to_numpy(), _matrix(vectors.field(1)), settings.k)
                yield pa.RecordBatch.from_arrays(list(map(pa.array, found)), names=["query_id", "vec_id", "score"])

    return run


def best_on_shelf(q_ids: np.ndarray, q: np.ndarray, floors: np.ndarray, v_ids: np.ndarray, v: np.ndarray, balls: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``best_pairs`` of queries and a shelf, stretch by stretch: a query passes over the stretches
    whose bound stays below its floor, which rises with its finds."""
    none = np.empty(0, np.int64)
    held, floors = (none, none, np.empty(0)), floors.copy()
    for ball in np.unique(balls):
        own = np.flatnonzero(balls == ball)
        centre, radius = stretch_bounds(v[own])
        asks = np.flatnonzero(reach_of(q, floors, centre[None, :], np.array([radius]))[:, 0])
        if not len(asks):
            continue
        ids, found, scores = best_pairs(q_ids[asks], q[asks], floors[asks], v_ids[own], v[own], k)
        held = tuple(map(np.concatenate, zip(held, (ids, found, scores), strict=True)))
        order = np.lexsort((held[1], -held[2], held[0]))
        held = tuple(x[order] for x in held)
        heads = np.searchsorted(held[0], held[0])
        place = np.arange(len(heads)) - heads
        held, place = tuple(x[place < k] for x in held), place[place < k]
        full = place == k - 1
        by_id = np.argsort(q_ids)
        at = by_id[np.searchsorted(q_ids[by_id], held[0][full])]
        floors[at] = np.maximum(floors[at], held[2][full])
    return held


def _shelf_kernel(settings: CurveSettings):
    def run(batches):
        for batch in batches:
            for row in range(batch.num_rows):
                queries, vectors = batch.column(0)[row].values, batch.column(1)[row].values
                q_ids, q = queries.field(0).to_numpy(), _matrix(queries.field(1))
                floors = queries.field(2).to_numpy(zero_copy_only=False)
                floors = np.where(np.isnan(floors), -np.inf, floors)
                v_ids, v, balls = vectors.field(0).to_numpy(), _matrix(vectors.field(1)), vectors.field(2).to_numpy()
                for lo in range(0, len(q_ids), settings.query_block):
                    cut = slice(lo, lo + settings.query_block)
                    found = best_on_shelf(q_ids[cut], q[cut], floors[cut], v_ids, v, balls, settings.k)
                    yield pa.RecordBatch.from_arrays(list(map(pa.array, found)), names=["query_id", "vec_id", "score"])

    return run


def usable_vectors(frame: DataFrame) -> DataFrame:
    """(vec_id, v: array of doubles, d: its length) of the rows that take part.

    Out are null ids, null vectors, vectors with null or non-finite components,
    and zero vectors.  Of rows that repeat an id the smallest vector counts.
    """
    v = F.transform("embedding", lambda x: x.cast("double"))
    rows = frame.where("vec_id is not null and embedding is not null").select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v"))
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists("v", lambda x: x != 0.0)
    rows = rows.where(F.coalesce(fine, F.lit(False)))
    return rows.groupBy("vec_id").agg(F.min("v").alias("v")).withColumn("d", F.size("v"))


def nearest(spark: SparkSession, frame: DataFrame, is_query, settings: CurveSettings = CurveSettings()) -> DataFrame:
    """query_id, rank, vec_id, score: the k candidates of largest inner product of each query.

    ``is_query`` is a Column over vec_id; candidates are all usable rows of the
    query's length but the query's own id.  Ties go to the smaller vec_id.  Fewer
    than k candidates give fewer rows; empty tables none; rows that repeat an id
    count once (the smallest vector); products that overflow are infinite, and
    rank lowest if undefined; extra columns are ignored, whatever their names.
    """
    work = Workspace(spark, "hilbert")
    rows = work.table("vectors", usable_vectors(frame))
    reach = rows.groupBy("d").agg(F.max(F.array_max(F.transform("v", F.abs))).alias("reach"))
    keys = rows.join(reach, "d").select("vec_id", "v", "d", "reach").mapInArrow(_key_kernel(settings), "vec_id long, d int, ordering int, key long")
    wanted = settings.partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    along = ["d", "ordering", "key", "vec_id"]
    ranged = keys.repartitionByRange(wanted, *along).sortWithinPartitions(*along)
    numbered = ranged.select("vec_id", "d", "ordering", F.spark_partition_id().alias("p"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("i"))
    numbered = work.table("numbered", numbered)
    # One row per partition, length and ordering: their running sums place every partition's rows.
    counts = numbered.groupBy("d", "ordering", "p").agg(F.count("*").alias("c"), F.min("i").alias("f"))
    before = Window.partitionBy("d", "ordering").orderBy("p").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("d", "ordering", "p", (F.coalesce(F.sum("c").over(before), F.lit(0)) - F.col("f")).alias("base"))
    at = F.col("i") + F.col("base")
    placed = numbered.join(F.broadcast(offsets) if wanted <= 10_000 else offsets, ["d", "ordering", "p"])
    placed = work.table("placed", placed.select("vec_id", "d", "ordering", F.floor(at / settings.block).cast("int").alias("block"), F.floor(at / settings.ball).cast("int").alias("ball")))
    work.drop("numbered")

    entry = F.collect_list(F.struct("vec_id", "v")).alias("vectors")
    queries = work.table("queries", rows.where(is_query))
    home = placed.join(_spread(queries.drop("d")), "vec_id")
    asks = home.select("vec_id", "v", "d", "ordering", F.explode(F.sequence(F.col("block") - settings.reach, F.col("block") + settings.reach)).alias("block"), F.lit(None).cast("double").alias("floor"))
    members = placed.join(_spread(rows.drop("d")), "vec_id").groupBy("d", "ordering", "block").agg(entry)  # at most `block` rows a group
    first = _meet(work, "first", asks, members, settings)
    found = work.table("found", _top(first.groupBy("query_id", "vec_id").agg(F.max("score").alias("score")), settings.k))
    work.drop("first")
    if settings.expand:
        floors = found.where(F.col("rank") == settings.k).select(F.col("query_id").alias("vec_id"), F.col("score").alias("floor"))
        asks = work.table("asks", queries.join(_spread(floors), "vec_id", "left").select("vec_id", "v", "d", "floor"))
        along = placed.where("ordering = 0").join(_spread(rows.drop("d")), "vec_id")
        bounds = along.groupBy("d", "ball").agg(F.collect_list("v").alias("vs")).mapInArrow(_ball_kernel, "d int, ball int, centre array<double>, radius double")  # at most `ball` rows a group
        bounds = work.table("bounds", bounds, 16)
        # Visits follow from centre and radius of each stretch; pieces of queries meet pieces of stretches.
        # A piece holds whole shelves.
        pieces = bounds.withColumn("piece", F.floor(F.col("ball") / (64 * settings.shelf)).cast("int")).groupBy("d", "piece").agg(F.collect_list(F.struct("ball", "centre", "radius")).alias("balls"))
        pieces = work.table("pieces", pieces, 16)  # at most 64 shelves a group
        sizes = asks.groupBy("d").agg(F.ceil(F.count("*") / settings.query_block).cast("int").alias("chunks"))
        reached = pieces.groupBy("d").agg(F.max("piece").alias("last"))
        chunks = asks.join(sizes, "d").withColumn("chunk", F.pmod(F.xxhash64("vec_id"), F.col("chunks")).cast("int")).groupBy("d", "chunk").agg(F.collect_list(F.struct("vec_id", "v", "floor")).alias("queries"))
        spread = chunks.join(reached, "d").withColumn("piece", F.explode(F.sequence(F.lit(0), F.col("last"))))
        visits = spread.join(_spread(pieces), ["d", "piece"]).select("d", "queries", "balls").mapInArrow(_visit_kernel(settings), "vec_id long, d int, shelf int")
        visits = work.table("visits", visits, 4)
        work.drop("pieces", "bounds")
        asks = visits.join(_spread(asks.drop("d")), "vec_id").select("vec_id", "v", "d", F.lit(0).alias("ordering"), F.col("shelf").alias("block"), "floor")
        shelves = along.groupBy("d", F.lit(0).alias("ordering"), F.floor(F.col("ball") / settings.shelf).cast("int").alias("block")).agg(F.collect_list(F.struct("vec_id", "v", "ball")).alias("vectors"))
        shelves = work.table("shelves", shelves, 2)
        wide = _meet(work, "wide", asks, shelves, settings, _shelf_kernel(settings), 4 * settings.query_block, 2)
        found = _top(wide.union(found.select("query_id", "vec_id", "score")).groupBy("query_id", "vec_id").agg(F.max("score").alias("score")), settings.k)
    result = work.table("result", found)
    work.keep("result")
    return result


def visited_share(spark: SparkSession, frame: DataFrame, is_query, settings: CurveSettings = CurveSettings()) -> dict:
    """What the search costs: rows that a query's windows hold at most, and usable rows (one job each)."""
    n = usable_vectors(frame).count()
    window = settings.orderings * (2 * settings.reach + 1) * settings.block
    return {"vectors": n, "window": window, "share": min(1.0, window / max(1, n))}


def _top(pairs: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = pairs.select("query_id", F.row_number().over(order).alias("rank"), "vec_id", "score")
    return ranked.where(F.col("rank") <= k)


def _spread(frame: DataFrame) -> DataFrame:
    """The frame as a side of a join that is dealt out, however small its files look: equal vectors
    make files a fraction of what a broadcast would hold on the driver."""
    return frame.hint("merge")


def _meet(work: Workspace, name: str, asks: DataFrame, members: DataFrame, settings: CurveSettings, kernel=None, block: int | None = None, batch: int = 16) -> DataFrame:
    """Scores of asked (query, d, ordering, block) meetings, the best k of each that reach the query's floor."""
    place = ["d", "ordering", "block"]
    sizes = asks.groupBy(*place).agg(F.count("*").alias("n"))
    parted = asks.join(_spread(sizes), place).withColumn("part", F.pmod(F.xxhash64("vec_id"), F.ceil(F.col("n") / (block or settings.query_block))).cast("int"))
    groups = parted.groupBy(*place, "part").agg(F.collect_list(F.struct("vec_id", "v", "floor")).alias("queries"))
    met = groups.join(_spread(members), place).select("queries", "vectors")
    return work.table(name, met.mapInArrow(kernel or _meet_kernel(settings), "query_id long, vec_id long, score double"), batch)


def stretch_bounds(v: np.ndarray) -> tuple[np.ndarray, float]:
    """Centre and radius of a stretch."""
    with np.errstate(over="ignore", invalid="ignore"):
        c = v.mean(0)
        return c, float(np.sqrt(((v - c) ** 2).sum(1).max())) * (1 + 1e-9)


def reach_of(q: np.ndarray, floors: np.ndarray, centres: np.ndarray, radii: np.ndarray) -> np.ndarray:
    """Whether each query has to visit each stretch; no floor, and no finite bound, mean a visit."""
    with np.errstate(over="ignore", invalid="ignore"):
        far = np.sqrt((q * q).sum(1))[:, None] * radii[None, :]
        near = q @ centres.T
        return ~(near + far + 1e-9 * (np.abs(near) + far) < floors[:, None])


def _ball_kernel(batches):
    for batch in batches:
        bounds = [stretch_bounds(_matrix(batch.column(2)[row].values)) for row in range(batch.num_rows)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([c for c, _ in bounds], pa.list_(pa.float64())), pa.array([r for _, r in bounds], pa.float64())], names=["d", "ball", "centre", "radius"])


def _visit_kernel(settings: CurveSettings):
    def run(batches):
        for batch in batches:
            for row in range(batch.num_rows):
                queries, balls = batch.column(1)[row].values, batch.column(2)[row].values
                visit = reach_of(_matrix(queries.field(1)), queries.field(2).to_numpy(zero_copy_only=False), _matrix(balls.field(1)), balls.field(2).to_numpy())
                places = balls.field(0).to_numpy() // settings.shelf
                for shelf in np.unique(places):
                    ask = np.flatnonzero(visit[:, places == shelf].any(1))
                    yield pa.RecordBatch.from_arrays([queries.field(0).take(pa.array(ask)), pa.array(np.full(len(ask), batch.column(0)[row].as_py(), np.int32)), pa.array(np.full(len(ask), shelf, np.int32))], names=["vec_id", "d", "shelf"])

    return run
