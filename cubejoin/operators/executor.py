"""The cube join: every variable partitioned, one exchange, a worst-case optimal join per cell."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from functools import reduce
from math import prod
from operator import and_

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.planner import GRID_ROWS, JoinPlan, auto_plan, fitted, quick_plan
from ..query import ConjunctiveQuery, fold_predicates
from ..sources.tables import dropped, run_folder, swept_shuffles, written
from ..plans.cost import communication_rows
from .kernel import CellCounters, CellJoin, KernelPlan, StoredAtom, join_cell, join_stored
from .shuffle import block_id, encode_domains, exchange, from_code, join_code, partition_id, partition_ids, route_once, route_rows, strides

#: Column of a result's multiplicity; no variable may have this name.
WEIGHT = "__weight"
PROFILE_SCHEMA = "cell int, rows_in long, rows_out long, probes long, comparisons long, visited array<long>, nodes_built long, index_bytes long, seconds double"


def _cells(batches):
    """(cell, table) of each cell, in order; buffers one cell at a time."""
    held: list[pa.RecordBatch] = []
    current = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cells = batch.column(0).to_numpy()
        turns = np.concatenate(([0], np.flatnonzero(cells[1:] != cells[:-1]) + 1, [len(cells)]))
        for lo, hi in zip(turns, turns[1:], strict=False):
            if current is not None and cells[lo] != current:
                yield current, pa.Table.from_batches(held)
                held = []
            current = int(cells[lo])
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield current, pa.Table.from_batches(held)


def _blocks(table: pa.Table, plan: KernelPlan) -> tuple[list[list[np.ndarray]], list[np.ndarray | None]]:
    """Columns (in any row order) and weights of each relation of a cell."""
    atoms = table.column("atom").to_numpy()
    columns = {n: table.column(n).to_numpy() for n in table.column_names if n not in ("cell", "atom")}
    blocks, held = [], []
    for j, scope in enumerate(plan.scopes):
        own = np.flatnonzero(atoms == j)
        blocks.append([columns[f"v{k}"][own].astype(np.int64) for k in range(len(scope))])
        held.append(columns["w"][own] if "w" in columns else None)
    return blocks, held


def _kernel(plan: KernelPlan, mode: str, limit: int | None):
    names = list(plan.order)

    def run(batches):
        for cell, table in _cells(batches):
            blocks, weights = _blocks(table, plan)
            del table
            found: list[pa.RecordBatch] = []

            def emit(columns, weight, found=found):
                if weight is None:
                    weight = np.ones(len(columns[0]), np.int64)
                found.append(pa.RecordBatch.from_arrays([*map(pa.array, columns), pa.array(weight)], names=[*names, WEIGHT]))

            if mode == "tuples" and limit is None and plan.index == "packed" and plan.search == "vector":
                yield from _streamed(plan, blocks, weights, names)
                continue
            total, counters = join_cell(plan, blocks, weights, emit if mode == "tuples" else None, limit)
            if mode == "tuples":
                yield from found
            elif mode == "count":
                yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["n"])
            else:
                yield _profile_row(cell, counters)

    return run


def _profile_row(cell: int, counters: CellCounters) -> pa.RecordBatch:
    row = {"cell": cell, **{k: getattr(counters, k) for k in ("rows_in", "rows_out", "probes", "comparisons", "visited", "nodes_built", "index_bytes", "seconds")}}
    kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.int64(), pa.int64(), pa.float64()]
    return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row.values(), kinds, strict=True)], names=list(row))


def _streamed(plan: KernelPlan, blocks, weights, names):
    """Result batches of a cell as they are found, one chunk at a time."""
    if any(len(b[0]) == 0 for b in blocks):
        return
    for columns, weight in CellJoin(plan, blocks, weights).results():
        weight = np.ones(len(columns[0]), np.int64) if weight is None else weight
        yield pa.RecordBatch.from_arrays([*map(pa.array, columns), pa.array(weight)], names=[*names, WEIGHT])


def bind_relations(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], only: Sequence[int] | None = None) -> tuple[ConjunctiveQuery, list[DataFrame | None], dict, DataFrame | None]:
    """Folded query, its relations with long codes, the kind of each variable, and the dictionary if one was needed.

    Columns that share a variable must have one kind (integers of any width are one).  ``only``
    names the atoms whose relations are wanted (None for the others): the rest read the same ones.
    """
    folded, frames = fold_predicates(query, relations)
    kinds: dict[str, object] = {}
    coded: dict[str, list[str]] = {}
    for j, atom in enumerate(folded.atoms):
        for v in atom.vars:
            kind = frames[f"r{j}"].schema[v].dataType
            direct = join_code(F.col(v), kind) is not None
            known = kinds.setdefault(v, kind)
            if (join_code(F.col(v), known) is not None) != direct or (not direct and known != kind):
                raise ValueError(f"variable {v} joins {known.simpleString()} with {kind.simpleString()}")
            if not direct and (only is None or j in only):
                coded.setdefault(f"r{j}", []).append(v)
    dictionary = None
    if coded:
        if len({kinds[v] for vs in coded.values() for v in vs}) > 1:
            frames = {k: f.select(*(F.col(v).cast("string").alias(v) if v in coded.get(k, ()) else F.col(v) for v in f.columns)) for k, f in frames.items()}
        frames, dictionary = encode_domains(frames, coded)
    out = []
    for j, atom in enumerate(folded.atoms):
        if only is not None and j not in only:
            out.append(None)
            continue
        frame = frames[f"r{j}"]
        columns = [F.col(v).cast("long").alias(v) if v in coded.get(f"r{j}", ()) else join_code(F.col(v), kinds[v]).alias(v) for v in atom.vars]
        out.append(frame.select(*columns))
    return folded, out, kinds, dictionary


def _routed(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], folded: ConjunctiveQuery, frames: list[DataFrame], dictionary: DataFrame | None, plan: JoinPlan) -> DataFrame:
    """Rows of all relations routed to their cells; a relation that several plain atoms read is passed over once."""
    order = plan.order
    scopes = [tuple(sorted(a.vars, key=order.index)) for a in folded.atoms]
    width = max(map(len, scopes))
    filtered = {frozenset(vs) for vs, _ in query.filters}
    shared: dict[str, list[int]] = {}
    if dictionary is None:
        for j, a in enumerate(query.atoms):
            alone = any(sum(v in b.vars for b in query.atoms) < 2 for v in a.vars)
            if not a.constants and len(set(a.vars)) == len(a.vars) and not alone and not any(f <= set(a.vars) for f in filtered):
                shared.setdefault(a.relation, []).append(j)
    parts, done = [], set()
    for name, atoms in shared.items():
        if len(atoms) > 1:
            frame = relations[name]
            longs = [join_code(F.col(f"`{c}`"), frame.schema[c].dataType).alias(f"c{k}") for k, c in enumerate(frame.columns)]
            base = frame.select(*longs).dropna()  # every variable is in another atom too
            parts.append(route_once(base, [(j, query.atoms[j].vars) for j in atoms], order, plan.shares, plan.hashing, width))
            done |= set(atoms)
    rest = [j for j in range(len(scopes)) if j not in done]
    if rest:
        routed = route_rows([frames[j] for j in rest], [scopes[j] for j in rest], order, plan.shares, plan.hashing, numbers=rest, width=width)
        parts.append(routed)
    return reduce(DataFrame.unionAll, parts)


def cube_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan | None = None, mode: str = "tuples", limit: int | None = None, profile: bool = False) -> DataFrame:
    """All bindings of the query (columns in head order), their number (``n``), or a work profile per cell.

    Sets: equal input rows count once.  Bags (``plan.semantics == 'bag'``):
    every input row counts and tuples repeat by their multiplicity.  ``limit``
    stops every cell and then the whole after so many results.  Without ``plan``
    the planner chooses order, shares, lifts, cells and executor from sketched
    statistics; a plan's ``executor`` and ``exchange`` are followed.  Counts of copies of
    one two-step path between the same ends (the four-cycle) are factorised.  Variables of
    strings and other non-integers travel as dictionary codes and come back as
    their values.
    """
    if plan is None and mode == "count" and limit is None and not profile:
        from .factorize import twin_path_count, twin_paths

        if twin_paths(query):
            return twin_path_count(spark, query, relations)
    if profile and plan is not None and limit is None:
        return cell_profiles(spark, query, relations, [plan])[0]
    plan = _sized(query, relations, plan or auto_plan(spark, query, relations), profile)
    if plan.exchange == "grid":
        return grid_join(spark, query, relations, plan, mode, limit)
    if plan.executor == "frontier" and plan.semantics != "bag" and not profile:
        from .frontier import frontier_join

        rows = frontier_join(spark, query, relations, plan, mode="tuples" if limit is not None else mode)
        return rows if limit is None else rows.limit(limit) if mode == "tuples" else rows.limit(limit).agg(F.count("*").alias("n"))
    if plan.exchange == "shared_files" and not profile and limit is None:
        return shared_files_join(spark, query, relations, plan, run_folder(spark, "blocks"), mode)
    folded, frames, kinds, dictionary = bind_relations(query, relations)
    order = plan.order
    scopes = [tuple(sorted(a.vars, key=order.index)) for a in folded.atoms]
    bag = plan.semantics == "bag"
    kernel = KernelPlan(order, tuple(scopes), tuple((x.level, x.at_depth, x.inputs) for x in plan.lifts), plan.index, plan.search, bag)
    routed = exchange(_routed(query, relations, folded, frames, dictionary, plan), plan.tasks or prod(plan.shares))
    if plan.executor == "grouped":
        if bag or limit is not None or profile:
            raise ValueError("the grouped executor takes sets without limit or profile")
        return _grouped(routed, kernel, folded, query, kinds, dictionary, mode)
    if profile:
        return routed.mapInArrow(_kernel(kernel, "profile", limit), PROFILE_SCHEMA)
    late = folded.filters
    if mode == "count" and not late:
        counts = routed.mapInArrow(_kernel(kernel, "count", limit), "n long")
        total = F.coalesce(F.sum("n"), F.lit(0)).cast("long")
        return counts.agg((F.least(total, F.lit(limit)) if limit is not None else total).alias("n"))
    schema = ", ".join([*(f"`{v}` long" for v in order), f"{WEIGHT} long"])
    rows = routed.mapInArrow(_kernel(kernel, "tuples", None if late else limit), schema)
    rows = decode(rows, query.head, kinds, dictionary)
    if late:
        rows = rows.where(reduce(and_, (condition(*(F.col(v) for v in vs)) for vs, condition in late)))
    if mode == "count":
        return rows.agg(F.coalesce(F.sum(WEIGHT), F.lit(0)).cast("long").alias("n"))
    if bag:
        rows = rows.withColumn("_", F.explode(F.sequence(F.lit(1).cast("long"), F.col(WEIGHT))))
    rows = rows.select(*query.head)
    return rows.limit(limit) if limit is not None else rows


def _sized(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan, profile: bool = False) -> JoinPlan:
    """The plan with cells that fit a worker and a block store instead of copies, where its rows are too many for
    the one exchange; other plans stay as they are.  A single cell, bags, profiles and other executors are taken as asked for."""
    if plan.exchange != "replicate" or plan.executor != "cube" or plan.semantics == "bag" or profile or plan.cells == 1 or any(len(a.vars) > 2 for a in query.atoms):
        return plan
    if "communication" in plan.costs:
        sizes = plan.costs.get("sizes")
        sent = plan.costs["communication"]["total"]
    else:
        counted = {name: relations[name].count() for name in {a.relation for a in query.atoms}}
        sizes = [counted[a.relation] for a in query.atoms]
        sent = communication_rows(query.scopes, sizes, plan.order, plan.shares)["total"]
    if sizes is None or sent <= GRID_ROWS:
        return plan
    return fitted(plan, query.scopes, sizes)


def decode(rows: DataFrame, head, kinds: Mapping, dictionary: DataFrame | None) -> DataFrame:
    """Codes back to values, keeping the other columns."""
    for v in head:
        if join_code(F.lit(None), kinds[v]) is not None:
            rows = rows.withColumn(v, from_code(F.col(v), kinds[v]))
        else:
            look = dictionary.select(F.col("value").alias("_value"), F.col("code").alias("_code"))
            rows = rows.join(look, F.col(v) == F.col("_code")).withColumn(v, F.col("_value").cast(kinds[v])).drop("_value", "_code")
    return rows


def count_by(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], pivot: str, plan: JoinPlan | None = None) -> DataFrame:
    """(pivot, c): results per value of one variable; chunks are aggregated where they are found, so no
    result leaves its cell.  Set semantics, no filters across atoms."""
    if fold_predicates(query, relations)[0].filters:
        raise ValueError("count_by takes no filters across atoms")
    plan = _sized(query, relations, plan or auto_plan(spark, query, relations))
    if plan.exchange == "grid":
        return grid_join(spark, query, relations, plan, pivot=pivot)
    folded, frames, kinds, dictionary = bind_relations(query, relations)
    order = plan.order
    scopes = [tuple(sorted(a.vars, key=order.index)) for a in folded.atoms]
    kernel = KernelPlan(order, tuple(scopes), tuple((x.level, x.at_depth, x.inputs) for x in plan.lifts))
    at = order.index(pivot)

    def run(batches):
        for _, table in _cells(batches):
            blocks, weights = _blocks(table, kernel)
            if any(len(b[0]) == 0 for b in blocks):
                continue
            for columns, _ in CellJoin(kernel, blocks, weights).results():
                values, counts = np.unique(columns[at], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(values), pa.array(counts)], names=[pivot, "c"])

    routed = exchange(_routed(query, relations, folded, frames, dictionary, plan), plan.tasks or prod(plan.shares))
    counted = routed.mapInArrow(run, f"`{pivot}` long, c long").groupBy(pivot).agg(F.sum("c").cast("long").alias("c"))
    return decode(counted, (pivot,), kinds, dictionary)


def cell_profile(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan) -> DataFrame:
    """Work of each non-empty cell, as each did it alone."""
    return cell_profiles(spark, query, relations, [plan])[0]


def cell_profiles(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plans: Sequence[JoinPlan]) -> list[DataFrame]:
    """``cell_profile`` of several plans.

    The cells are the plan's, whatever they hold.  Where their rows are too many to be copied, each cell reads
    them from a block store, which plans that deal alike share, and joins them over a compact index.
    """
    counted: dict[str, int] = {}
    large: dict[tuple, list[int]] = {}
    out: list[DataFrame | None] = [None] * len(plans)
    for k, plan in enumerate(plans):
        if plan.executor == "cube" and plan.exchange in ("replicate", "grid") and plan.semantics != "bag" and (plan.index, plan.search) == ("packed", "vector"):
            counted = counted or {name: relations[name].count() for name in {a.relation for a in query.atoms}}
            if communication_rows(query.scopes, [counted[a.relation] for a in query.atoms], plan.order, plan.shares)["total"] > GRID_ROWS:
                large.setdefault((plan.order, plan.shares, plan.hashing), []).append(k)
                continue
        out[k] = _routed_profile(query, relations, plan)
    for alike in large.values():
        for k, profile in zip(alike, _stored_profiles(spark, query, relations, [plans[k] for k in alike]), strict=True):
            out[k] = profile
    return out


def _routed_profile(query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan) -> DataFrame:
    folded, frames, _, dictionary = bind_relations(query, relations)
    scopes = tuple(tuple(sorted(a.vars, key=plan.order.index)) for a in folded.atoms)
    kernel = KernelPlan(plan.order, scopes, tuple((x.level, x.at_depth, x.inputs) for x in plan.lifts), plan.index, plan.search, plan.semantics == "bag")
    routed = exchange(_routed(query, relations, folded, frames, dictionary, plan), plan.tasks or prod(plan.shares))
    return routed.mapInArrow(_kernel(kernel, "profile", None), PROFILE_SCHEMA)


#: Blocks that one store may have; beyond these every atom gets its own.
STORE_BLOCKS = 1024
#: Rows of a block that one task sorts, about; a larger block is several files.
SORTED_ROWS = 1_500_000


def _stored_profiles(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plans: Sequence[JoinPlan]) -> list[DataFrame]:
    """Profiles of plans with the same cells, made at once; the store goes when they are written."""
    order, shares, hashing = plans[0].order, plans[0].shares, plans[0].hashing
    stands = _stands(query, relations)
    folded, frames, _, _ = bind_relations(query, relations, sorted(set(stands)))
    digits = _digits(folded, order, shares, stands)
    if any(prod(p for column in d for p, _ in column) > STORE_BLOCKS for d in digits.values()):
        stands = list(range(len(stands)))
        folded, frames, _, _ = bind_relations(query, relations)
        digits = _digits(folded, order, shares, stands)
    stores, blocks = {}, {}
    for k, own in digits.items():
        stores[k] = run_folder(spark, "profiled")
        names = folded.atoms[k].vars
        blocks[k] = write_counted(spark, frames[k].select(*(F.col(v).alias(f"c{i}") for i, v in enumerate(names))).dropna(), own, hashing, stores[k])
    atoms = [(stores[k], digits[k], blocks[k], folded.atoms[j].vars) for j, k in enumerate(stands)]
    scopes = tuple(tuple(sorted(a.vars, key=order.index)) for a in folded.atoms)
    kernels = [KernelPlan(order, scopes, tuple((x.level, x.at_depth, x.inputs) for x in p.lifts), p.index, p.search, False) for p in plans]
    read = _cell_reader(order, shares, atoms)

    def run(batches):
        for batch in batches:
            for number in batch.column(0).to_pylist():
                cell, k = divmod(number, len(kernels))
                held = read(cell, kernels[k].scopes)
                if any(a.rows for a in held):
                    out = _profile_row(cell, join_stored(kernels[k], held))
                    yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), *out.columns], names=["plan", *out.schema.names])

    many = prod(shares) * len(plans)
    cells = spark.range(0, many, 1, min(many, max(64, 8 * spark.sparkContext.defaultParallelism)))
    found = written(spark, cells.mapInArrow(run, f"plan int, {PROFILE_SCHEMA}"), "profile")
    for store in stores.values():
        dropped(store)
    return [found.where(F.col("plan") == k).drop("plan") for k in range(len(plans))]


def _stands(query: ConjunctiveQuery, relations: Mapping[str, DataFrame]) -> list[int]:
    """For each atom the one whose stored rows it reads: one atom a relation stands for all plain ones over it."""
    filtered = {frozenset(vs) for vs, _ in query.filters}
    plain = [not a.constants and len(set(a.vars)) == len(a.vars) and not any(f <= set(a.vars) for f in filtered) for a in query.atoms]
    alike = {name: tuple(relations[name].schema[c].dataType for c in relations[name].columns) for name in relations}
    first: dict[str, int] = {}
    return [first.setdefault(a.relation, j) if plain[j] and len(set(map(str, alike[a.relation]))) == 1 else j for j, a in enumerate(query.atoms)]


def _digits(folded: ConjunctiveQuery, order: Sequence[str], shares: Sequence[int], stands: Sequence[int]) -> dict[int, list[list[tuple[int, int]]]]:
    """For each stored relation and column the (share, seed) of all variables that atoms give it."""
    out: dict[int, list[list[tuple[int, int]]]] = {}
    for j, k in enumerate(stands):
        held = out.setdefault(k, [[] for _ in folded.atoms[j].vars])
        for column, v in zip(held, folded.atoms[j].vars, strict=True):
            at = list(order).index(v)
            if shares[at] > 1 and (shares[at], at + 1) not in column:
                column.append((shares[at], at + 1))
    return out


def write_counted(spark: SparkSession, base: DataFrame, digits: list[list[tuple[int, int]]], hashing: str, path: str) -> dict[int, tuple]:
    """A relation of longs dealt into blocks by the partitions of its columns' values, sorted and without repeats, one folder a
    block: (rows, repeats included, then the least and the greatest value of each column) by block."""
    block, blocks = F.lit(0), 1
    names = [f"c{k}" for k in range(len(digits))]
    for name, column in zip(names, digits, strict=True):
        for share, seed in column:
            block = block * F.lit(share) + partition_id(F.col(name), share, seed, hashing)
            blocks *= share
    marked = base.select(block.cast("int").alias("block"), *names)
    ends = [f(F.col(c)).alias(f"{n}_{c}") for c in names for n, f in (("lo", F.min), ("hi", F.max))]
    counted = {r.block: (r.n, *((r[f"lo_{c}"], r[f"hi_{c}"]) for c in names)) for r in marked.groupBy("block").agg(F.count("*").alias("n"), *ends).collect()}
    narrow = all(lo >= -(1 << 31) and hi < 1 << 31 for _, *columns in counted.values() for lo, hi in columns)
    kind, arrow = ("int", pa.int32()) if narrow else ("long", pa.int64())
    parts = -(-max((r[0] for r in counted.values()), default=1) // SORTED_ROWS)
    task = F.col("block") * F.lit(parts) + partition_id(F.xxhash64(*names), parts, 0)
    dealt = marked.select("block", *(F.col(c).cast(kind) for c in names)).repartitionById(blocks * parts, task)
    rows = dealt.mapInArrow(_sorted_block(len(names), arrow), f"block int, {', '.join(f'{c} {kind}' for c in names)}")
    with swept_shuffles(spark):
        rows.write.partitionBy("block").parquet(path)
    return counted


def _cell_reader(order: tuple[str, ...], shares: tuple[int, ...], atoms: list[tuple[str, list, dict[int, tuple], tuple[str, ...]]]):
    """A cell's number and its scopes to its atoms as they are stored: atom = (store, its digits, its blocks, variable of each column)."""
    step = strides(shares)

    def read(cell: int, scopes) -> list[StoredAtom]:
        import pyarrow.fs as pafs
        import pyarrow.parquet as pq

        out = []
        for (store, digits, blocks, columns), scope in zip(atoms, scopes, strict=True):
            numbers = [0]
            for v, column in zip(columns, digits, strict=True):
                at = order.index(v)
                for share, seed in column:
                    mine = [cell // step[at] % share] if seed == at + 1 else range(share)
                    numbers = [n * share + x for n in numbers for x in mine]
            held = [n for n in numbers if n in blocks]
            system, root = pafs.FileSystem.from_uri(store if "://" in store or store.startswith("file:") else f"file://{store}")
            files = [f.path for n in held for f in system.get_file_info(pafs.FileSelector(f"{root}/block={n}")) if f.path.endswith(".parquet")]
            place = [columns.index(v) for v in scope]

            def parts(system=system, files=files, place=place):
                for path in files:
                    with system.open_input_file(path) as file:
                        stored = pq.ParquetFile(file)
                        for group in range(stored.num_row_groups):
                            table = stored.read_row_group(group, use_threads=False)
                            yield [table.column(f"c{k}").to_numpy() for k in place]

            rows = 0
            for path in files:
                with system.open_input_file(path) as file:
                    rows += pq.ParquetFile(file).metadata.num_rows
            ends = [(min(blocks[n][1 + k][0] for n in held), max(blocks[n][1 + k][1] for n in held)) if held else (0, 0) for k in place]
            out.append(StoredAtom(sum(blocks[n][0] for n in held), rows, ends, parts))
        return out

    return read


def _grouped(routed: DataFrame, kernel: KernelPlan, folded: ConjunctiveQuery, query: ConjunctiveQuery, kinds: Mapping, dictionary: DataFrame | None, mode: str) -> DataFrame:
    """The cells as groups of ``applyInArrow``: Spark forms each cell's table, the kernel joins it."""
    names = list(kernel.order)

    def join(table: pa.Table) -> pa.Table:
        blocks, weights = _blocks(table, kernel)
        found = list(_streamed(kernel, blocks, weights, names))
        schema = pa.schema([*((n, pa.int64()) for n in names), (WEIGHT, pa.int64())])
        return pa.Table.from_batches(found, schema)

    schema = ", ".join([*(f"`{v}` long" for v in names), f"{WEIGHT} long"])
    rows = decode(routed.groupBy("cell").applyInArrow(join, schema), query.head, kinds, dictionary)
    for vs, condition in folded.filters:
        rows = rows.where(condition(*(F.col(v) for v in vs)))
    return rows.agg(F.count("*").alias("n")) if mode == "count" else rows.select(*query.head)


def _block_reader(path: str, order: tuple[str, ...], shares: tuple[int, ...], scopes: list[tuple[str, ...]], kernel: KernelPlan, mode: str):
    """Cell numbers to results: each cell opens the files of its own blocks and no others."""
    names = list(order)

    def run(batches):
        import pyarrow.fs as pafs
        import pyarrow.parquet as pq

        system, root = pafs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")
        step = strides(shares)
        total = 0
        for batch in batches:
            for cell in batch.column(0).to_pylist():
                where = {v: cell // step[k] % shares[k] for k, v in enumerate(order)}
                blocks = []
                for j, scope in enumerate(scopes):
                    block = 0
                    for v in scope:
                        block = block * shares[order.index(v)] + where[v]
                    listed = system.get_file_info(pafs.FileSelector(f"{root}/atom={j}/block={block}", allow_not_found=True))
                    files = [f.path for f in listed if f.path.endswith(".parquet")]
                    if not files:
                        break
                    parts = [pq.ParquetFile(system.open_input_file(f)).read() for f in files]
                    blocks.append([np.concatenate([p.column(f"v{k}").to_numpy() for p in parts]) for k in range(len(scope))])
                if len(blocks) < len(scopes):
                    continue  # an empty block: nothing to join
                if mode == "count":
                    total += join_cell(kernel, blocks, [None] * len(blocks))[0]
                else:
                    yield from _streamed(kernel, blocks, [None] * len(blocks), names)
        if mode == "count":
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["n"])

    return run


def _sorted_block(width: int, kind: pa.DataType):
    """The rows of one block, sorted by their columns and without repeats."""

    def run(batches):
        held = list(batches)
        if not held:
            return
        table = pa.Table.from_batches(held)
        del held
        columns = [table.column(f"c{k}").to_numpy().astype(np.int64) for k in range(width)]
        blocks = table.column("block").to_numpy()
        for block in np.unique(blocks):  # one, unless blocks share a task
            own = columns if len(blocks) and blocks[0] == blocks[-1] and (blocks == block).all() else [c[blocks == block] for c in columns]
            order = np.lexsort(own[::-1])
            own = [c[order] for c in own]
            fresh = np.ones(len(order), bool)
            fresh[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in own])
            for lo in range(0, len(order), 1 << 20):
                part = [c[lo : lo + (1 << 20)][fresh[lo : lo + (1 << 20)]] for c in own]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part[0]), block, np.int32)), *(pa.array(c.astype(np.int32) if kind == pa.int32() else c) for c in part)], names=["block", *(f"c{k}" for k in range(width))])

    return run


def write_grid(spark: SparkSession, base: DataFrame, sides: tuple[int, ...], hashing: str, path: str, most: int | None = None) -> None:
    """A relation of longs (c0, c1, ...) dealt into a grid of blocks, ``sides`` parts a column, sorted, one folder a block.

    All columns are dealt by one function, whatever variable an atom gives
    them, so that every atom over the relation reads the same blocks.  Where
    the values are codes from 0 to ``most``, no pass over them looks for their ends.
    """
    block = F.lit(0)
    for k, side in enumerate(sides):
        block = block * F.lit(side) + partition_id(F.col(f"c{k}"), side, 0, hashing)
    names = [f"c{k}" for k in range(len(sides))]
    ends = {f"{n}_{c}": x for c in names for n, x in (("lo", 0), ("hi", most))}
    if most is None:
        ends = base.agg(*(f(F.col(c)).alias(f"{n}_{c}") for c in names for n, f in (("lo", F.min), ("hi", F.max)))).first()
    narrow = all(ends[f"lo_{c}"] is None or (ends[f"lo_{c}"] >= -(1 << 31) and ends[f"hi_{c}"] < 1 << 31) for c in names)
    kind, arrow = ("int", pa.int32()) if narrow else ("long", pa.int64())
    dealt = base.select(block.cast("int").alias("block"), *(F.col(c).cast(kind).alias(c) for c in names)).repartitionById(prod(sides), F.col("block"))
    rows = dealt.mapInArrow(_sorted_block(len(sides), arrow), f"block int, {', '.join(f'{c} {kind}' for c in names)}")
    with swept_shuffles(spark):
        rows.write.partitionBy("block").parquet(path)


def _grid_reader(order: tuple[str, ...], shares: tuple[int, ...], atoms: list[tuple[str, tuple[int, ...], tuple[str, ...]]], hashing: str):
    """Cell numbers to (cell, blocks of all atoms): atom = (store, its sides, variable of each column).

    A share may be smaller than a side (then a cell reads several parts), never
    larger.  Blocks that the next cell needs again are kept.
    """
    step = strides(shares)

    def run(batches):
        import pyarrow.fs as pafs
        import pyarrow.parquet as pq

        systems: dict[str, tuple] = {}
        held: dict[tuple, list[np.ndarray] | None] = {}

        def read(store: str, block: int) -> list[np.ndarray] | None:
            if store not in systems:
                systems[store] = pafs.FileSystem.from_uri(store if "://" in store or store.startswith("file:") else f"file://{store}")
            system, root = systems[store]
            listed = system.get_file_info(pafs.FileSelector(f"{root}/block={block}", allow_not_found=True))
            tables = [pq.ParquetFile(system.open_input_file(f.path)).read(use_threads=False) for f in listed if f.path.endswith(".parquet")]
            if not tables:
                return None
            return [np.concatenate([t.column(c).to_numpy() for t in tables]) if len(tables) > 1 else tables[0].column(c).to_numpy() for c in tables[0].column_names]

        for batch in batches:
            for cell in batch.column(0).to_pylist():
                where = {v: cell // step[k] % shares[k] for k, v in enumerate(order)}
                blocks, used = [], {}
                for store, sides, columns in atoms:
                    numbers = [0]
                    for v, side in zip(columns, sides, strict=True):
                        numbers = [n * side + at for n in numbers for at in range(where[v], side, shares[order.index(v)])]
                    parts = []
                    for n in numbers:
                        if (store, n) not in used:
                            used[store, n] = held[store, n] if (store, n) in held else read(store, n)
                        if used[store, n] is not None:
                            parts.append(used[store, n])
                    if not parts:
                        blocks = None  # an empty block: nothing to join
                        break
                    place = {v: k for k, v in enumerate(columns)}
                    scope = sorted(columns, key=order.index)
                    blocks.append([(np.concatenate([p[place[v]] for p in parts]) if len(parts) > 1 else parts[0][place[v]]).astype(np.int64) for v in scope])
                held = used if len(used) <= 2 * len(atoms) else {}
                if blocks is not None:
                    del used
                    yield cell, blocks

    return run


def _grid(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan):
    """(folded query, kinds, dictionary, reader of cells' blocks) with every relation stored once, whichever atoms read it."""
    shares = dict(zip(plan.order, plan.shares, strict=True))
    stands = _stands(query, relations)  # folding and coding are done for these only
    folded, frames, kinds, dictionary = bind_relations(query, relations, sorted(set(stands)))
    sides: dict[int, list[int]] = {}
    for j, k in enumerate(stands):
        own = [shares[v] for v in folded.atoms[j].vars]
        sides[k] = [max(pair) for pair in zip(sides.get(k, own), own, strict=True)]
    stores = {}
    words = dictionary.count() if dictionary is not None else 0
    for k, own in sides.items():
        stores[k] = run_folder(spark, "grid")
        names = folded.atoms[k].vars
        coded = all(join_code(F.lit(None), kinds[v]) is None for v in names)
        write_grid(spark, frames[k].select(*(F.col(v).alias(f"c{i}") for i, v in enumerate(names))).dropna(), tuple(own), plan.hashing, stores[k], *([words] if coded else []))
    atoms = [(stores[k], tuple(sides[k]), folded.atoms[j].vars) for j, k in enumerate(stands)]
    return folded, kinds, dictionary, _grid_reader(plan.order, plan.shares, atoms, plan.hashing)


def grid_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan, mode: str = "tuples", limit: int | None = None, pivot: str | None = None) -> DataFrame:
    """Cube join over a block store that all atoms of a relation share: each relation is shuffled and
    written once, however many atoms read it and however many cells there are, so disk does not grow with either.

    With ``pivot``, (pivot, c) as by ``count_by``.  Sets only; filters across atoms act on the results.
    """
    folded, kinds, dictionary, read = _grid(spark, query, relations, plan)
    order = plan.order
    scopes = [tuple(sorted(a.vars, key=order.index)) for a in folded.atoms]
    kernel = KernelPlan(order, tuple(scopes), tuple((x.level, x.at_depth, x.inputs) for x in plan.lifts), plan.index, plan.search, False)
    late = folded.filters
    counting = mode == "count" and not late
    names = list(order)

    def run(batches):
        total = 0
        for _, blocks in read(batches):
            none = [None] * len(blocks)
            if pivot is not None:
                for columns, _ in CellJoin(kernel, blocks, none).results():
                    values, counts = np.unique(columns[order.index(pivot)], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(values), pa.array(counts)], names=[pivot, "c"])
            elif counting:
                total += join_cell(kernel, blocks, none, None, limit)[0]
                if limit is not None and total >= limit:
                    break
            elif plan.search == "hashed" or (plan.index == "packed" and plan.search == "vector"):
                for columns, _ in CellJoin(kernel, blocks, none).results(None if late else limit):
                    yield pa.RecordBatch.from_arrays([*map(pa.array, columns), pa.array(np.ones(len(columns[0]), np.int64))], names=[*names, WEIGHT])
            else:
                found: list = []
                join_cell(kernel, blocks, none, lambda columns, _, found=found: found.append(columns), None if late else limit)
                for columns in found:
                    yield pa.RecordBatch.from_arrays([*map(pa.array, columns), pa.array(np.ones(len(columns[0]), np.int64))], names=[*names, WEIGHT])
        if counting and pivot is None:
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["n"])

    cells = spark.range(0, plan.cells, 1, min(plan.cells, max(64, 8 * spark.sparkContext.defaultParallelism)))
    if pivot is not None:
        return decode(cells.mapInArrow(run, f"`{pivot}` long, c long").groupBy(pivot).agg(F.sum("c").cast("long").alias("c")), (pivot,), kinds, dictionary)
    if counting:
        total = F.coalesce(F.sum("n"), F.lit(0)).cast("long")
        return cells.mapInArrow(run, "n long").agg((F.least(total, F.lit(limit)) if limit is not None else total).alias("n"))
    rows = cells.mapInArrow(run, ", ".join([*(f"`{v}` long" for v in order), f"{WEIGHT} long"]))
    rows = decode(rows, query.head, kinds, dictionary)
    for vs, condition in late:
        rows = rows.where(condition(*(F.col(v) for v in vs)))
    if limit is not None:
        rows = rows.limit(limit)
    return rows.agg(F.count("*").alias("n")) if mode == "count" else rows.select(*query.head)


def shared_files_join(spark: SparkSession, query: ConjunctiveQuery, relations: Mapping[str, DataFrame], plan: JoinPlan, path: str, mode: str = "count") -> DataFrame:
    """Cube join over a block store: every relation is shuffled and written once, without copies, as one
    folder per block; a task is a cell number and reads the files of the blocks that agree with it.

    Neither stored nor shuffled bytes grow with the number of cells; what grows
    is reading.  ``path`` must be readable by pyarrow on the executors (local,
    HDFS, S3, GCS).  Sets only; filters across atoms act on the results.
    """
    if plan.semantics == "bag":
        raise ValueError("the shared-files exchange joins sets")
    folded, frames, kinds, dictionary = bind_relations(query, relations)
    order, shares = plan.order, plan.shares
    scopes = [tuple(sorted(a.vars, key=order.index)) for a in folded.atoms]
    for j, scope in enumerate(scopes):
        marked = partition_ids(frames[j], scope, order, shares, plan.hashing).withColumn("block", block_id(scope, order, shares))
        stored = marked.select("block", *(F.col(v).alias(f"v{k}") for k, v in enumerate(scope)))
        stored.repartition("block").write.mode("overwrite").partitionBy("block").parquet(f"{path}/atom={j}")
    kernel = KernelPlan(order, tuple(scopes), tuple((x.level, x.at_depth, x.inputs) for x in plan.lifts), plan.index, plan.search, False)
    late = folded.filters
    read = _block_reader(path, order, shares, scopes, kernel, "tuples" if late else mode)
    cells = spark.range(0, prod(shares), 1, min(prod(shares), plan.tasks or prod(shares)))
    if mode == "count" and not late:
        return cells.mapInArrow(read, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
    schema = ", ".join([*(f"`{v}` long" for v in order), f"{WEIGHT} long"])
    rows = decode(cells.mapInArrow(read, schema), query.head, kinds, dictionary)
    for vs, condition in late:
        rows = rows.where(condition(*(F.col(v) for v in vs)))
    return rows.agg(F.count("*").alias("n")) if mode == "count" else rows.select(*query.head)
