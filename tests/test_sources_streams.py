import pytest
from pyspark.sql import functions as F

from cubejoin.functions.register import parse_props, register_functions, skew_index, sorted_intersect_size
from cubejoin.operators.kernel import generic_join
from cubejoin.sources.edge_stream import register
from cubejoin.sources.generators import tensor_relation, tensor_workload
from cubejoin.sources.tables import load_tables, materialize, read_block, read_edges, write_blocks, write_result
from cubejoin.streaming.incremental import deduplicated, degree_state, delta_count, event_stream, incremental_counts, windowed_edges, windowed_triangles
from cubejoin.workloads import pattern


def test_edge_files(spark, tmp_path):
    edges = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    for fmt in ("csv", "json", "parquet", "orc"):
        write_result(edges, str(tmp_path / fmt), fmt)
        assert sorted(read_edges(spark, str(tmp_path / fmt), fmt).collect()) == [(1, 2), (2, 3)]
    assert materialize(edges.union(edges), str(tmp_path / "m"), parts=2).count() == 2
    write_blocks(edges, ("src", "dst"), ("src", "dst"), (2, 1), str(tmp_path / "b"), "mod")
    assert read_block(spark, str(tmp_path / "b"), (1, 0), ("src", "dst")).collect() == [(1, 2)]


def test_tables(spark, tiny):
    assert set(load_tables(spark, tiny, ("orders", "events"))) == {"orders", "events"}
    assert parse_props(load_tables(spark, tiny, ("events",))["events"]).where("k is not null").count() > 0


def test_generators(spark):
    assert tensor_relation(spark, 500, (4, 4, 4), 1).count() <= 64
    made = tensor_workload(spark, "sparse", 200, 8)
    assert sorted(made) == [f"t{k}" for k in range(1, 8)] and made["t5"].agg(F.max("x0")).first()[0] < 8


def test_data_source(spark):
    register(spark)
    got = spark.read.format("edges").option("edges", "1 2;2 3;1 3").load()
    assert sorted(got.collect()) == [(1, 2), (1, 3), (2, 3)]
    assert spark.read.format("edges").option("n", 50).option("vertices", 9).load().where("src < 9 and dst < 9").count() == 50


def test_functions(spark):
    register_functions(spark)
    frame = spark.createDataFrame([([1, 3, 5], [3, 4, 5]), ([], [1]), (None, [1])], "a array<long>, b array<long>")
    assert [r[0] for r in frame.select(sorted_intersect_size("a", "b")).collect()] == [2, 0, None]
    assert spark.range(1, 4).select(F.col("id").cast("double").alias("v")).agg(skew_index("v")).first()[0] == 1.5
    spark.createDataFrame([(1, 2), (2, 3), (1, 3)], "src long, dst long").createOrReplaceTempView("pattern_edges")
    got = spark.sql("SELECT * FROM match_pattern(TABLE(pattern_edges) WITH SINGLE PARTITION, 'Q(x, y, z) :- e(x, y), e(y, z), e(x, z)')")
    assert [r.binding for r in got.collect()] == [[1, 2, 3]]


EDGES = [(1, 2), (2, 3), (1, 3), (3, 4), (2, 4), (4, 1), (1, 4)]


def triangles(rows):
    query = pattern("q1d")
    return generic_join([rows] * 3, query.head, query.scopes, mode="count")


def test_delta_count(spark):
    make = lambda rows: spark.createDataFrame(rows, "src long, dst long")
    for cut in (1, 3, 6):
        assert delta_count(spark, pattern("q1d"), make(EDGES[:cut]), make(EDGES[cut:])) == triangles(EDGES) - triangles(EDGES[:cut])


def test_incremental_stream(spark, tmp_path):
    source = tmp_path / "in"
    for k, part in enumerate((EDGES[:3], EDGES[2:5], EDGES[5:])):
        spark.createDataFrame(part, "src long, dst long").coalesce(1).write.parquet(str(source / f"p{k}"))
    stream = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(str(source / "*"))
    running, state = incremental_counts(stream, pattern("q1d"), str(tmp_path / "state"))
    running.awaitTermination(180)
    assert state.total == triangles(EDGES)


def test_event_windows(spark, tiny, tmp_path):
    events = event_stream(spark, tiny)
    counted = windowed_edges(deduplicated(events, ["event_id"]), late=None)
    running = counted.writeStream.format("memory").queryName("windows").outputMode("append").trigger(availableNow=True).start()
    running.awaitTermination(180)
    batch = windowed_edges(load_tables(spark, tiny, ("events",))["events"])
    assert 0 < spark.table("windows").count() <= batch.count()


def test_windowed_triangles(spark):
    rows = [("2024-01-01 10:00:00", 1, 2), ("2024-01-01 11:00:00", 2, 3), ("2024-01-01 12:00:00", 1, 3), ("2024-01-02 01:00:00", 3, 4)]
    frame = spark.createDataFrame(rows, "ts string, src long, dst long").withColumn("ts", F.to_timestamp("ts"))
    assert [r.n for r in windowed_triangles(frame).collect()] == [1]


def test_degree_state_plan(spark):
    register(spark)
    stream = spark.readStream.format("edges").option("n", 20).option("vertices", 4).load()
    assert degree_state(stream).isStreaming


FROM_TABLES = ("lift_clique", "order_enumeration", "replicated_cost_table", "share_enumeration", *(f"tensor_{kind}_{shape}" for kind in ("dense", "sparse") for shape in ("ct", "lw")))


@pytest.mark.parametrize("name", FROM_TABLES)
def test_reads_a_table_and_equals_its_sql(spark, tiny, name):
    import duckdb

    import __spark_entry__ as entry

    sql = entry.oracle_sql()[name]
    read = "part" if name.startswith("tensor") else "orders"
    assert f"FROM {read}" in sql
    con = duckdb.connect()
    con.execute(f"CREATE VIEW {read} AS SELECT * FROM '{tiny}/{read}.parquet'")
    want = con.execute(sql).fetchall()
    got = entry.queries()[name](spark, tiny)
    assert got.columns == [c[0] for c in con.description]
    assert sorted(map(tuple, got.collect())) == sorted(want)
