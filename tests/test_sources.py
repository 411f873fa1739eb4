import numpy as np
import pytest
from pyspark.sql import functions as F

from motifscan.operators import relational, schemes
from motifscan.sources import graphs, tables
from motifscan.streaming import edges as st


@pytest.mark.parametrize("fmt", ["parquet", "orc", "json", "csv", "text"])
def test_edge_lists(spark, tmp_path, fmt):
    path = str(tmp_path / fmt)
    df = spark.createDataFrame([(1, 2), (3, 4)], "src long, dst long")
    if fmt == "text":
        df.select(F.concat_ws(" ", "src", "dst")).write.text(path)
    else:
        df.write.format(fmt).save(path)
    assert sorted(map(tuple, tables.read_edges(spark, path, fmt).collect())) == [(1, 2), (3, 4)]


def test_string_nodes(spark):
    e, names = tables.number_nodes(spark.createDataFrame([("a", "b"), ("b", "c")], "x string, y string"), "x", "y")
    assert e.count() == 2 and {r["name"] for r in names.collect()} == {"a", "b", "c"}


def test_groups(spark):
    f = spark.createDataFrame([(1, 5), (1, 6), (1, 6), (2, 5), (2, 6), (3, 7), (None, 9), (1, None)], "g long, v long")
    assert [tuple(r) for r in graphs.co_membership_edges(f, "g", "v").collect()] == [(5, 6)]
    with pytest.raises(Exception, match="more than 1"):
        graphs.co_membership_edges(f, "g", "v", max_group=1).collect()
    assert graphs.oversized_groups(f, "g", "v", 1).count() == 2


def test_trimming(spark):
    g = graphs.DataGraph.from_df(spark.createDataFrame([(1, 2), (2, 3), (1, 3), (3, 4), (4, 5)], "src long, dst long"))
    assert g.with_min_degree(2).edges.count() == 3


def test_page_links_and_sink(spark, sf, tmp_path):
    links = tables.page_links(tables.load(spark, sf, "pages"))
    tables.write_instances(links, str(tmp_path / "o"))
    assert spark.read.parquet(str(tmp_path / "o")).columns == ["from_host", "to_host"]


def test_similarity_edges(spark):
    v = spark.createDataFrame([(1, [1.0, 0.0]), (2, [1.0, 0.01]), (3, [0.0, 1.0]), (4, [0.0, 0.0]), (5, None), (6, [1.0, 0.0, 0.0])], "vec_id long, embedding array<double>")
    for exact in (False, True):
        assert [tuple(r) for r in graphs.similarity_edges(v, 0.99, exact=exact).collect()] == [(1, 2)]


def test_similarity_recall(spark):
    rng = np.random.default_rng(3)
    centres = rng.normal(size=(40, 16))
    rows = [(i, (centres[i % 40] + 0.25 * rng.normal(size=16)).tolist()) for i in range(400)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got, want = ({tuple(r) for r in graphs.similarity_edges(df, 0.9, exact=exact).collect()} for exact in (False, True))
    x = np.array([r[1] for r in rows])
    x /= np.sqrt((x * x).sum(1, keepdims=True))
    assert want == {(i, j) for i, j in zip(*np.nonzero(x @ x.T >= 0.9), strict=True) if i < j}
    assert got <= want and len(got) >= 0.9 * len(want) > 0
    bits, tables = graphs.sign_tables(10**9, 0.9)
    assert bits == 21 and tables < 100 and graphs.sign_tables(100, 0.9)[0] == 4


def test_new_triangles_of_a_stream(spark, tmp_path):
    path = str(tmp_path / "in")
    spark.createDataFrame([(1, 2), (2, 3), (1, 3), (1, 3), (3, 4)], "src long, dst long").coalesce(1).write.parquet(path)
    edges = spark.readStream.schema("src long, dst long").parquet(path)
    found = st.run_to_table(st.new_triangles(schemes.multiset_keys(edges, 2, 3), 2), "new_triangles", "append", str(tmp_path / "c"))
    own = found.where(schemes.multiset_owner(["x0", "x1", "x2"], 2) == F.col("rk"))
    assert [tuple(r)[1:] for r in own.collect()] == [(1, 2, 3)]


def test_sessions_and_intervals(spark, sf, tmp_path):
    ev = st.event_stream(spark, sf)
    n = st.run_to_table(st.user_sessions(ev), "sessions", "append", str(tmp_path / "s")).count()
    assert n > 0
    assert st.run_to_table(st.interval_pairs(ev), "pairs", "append", str(tmp_path / "p")).where("src >= dst").count() == 0


def test_old_edges_are_forgotten(spark, tmp_path):
    """With a time to live, an edge that is too old closes no triangle."""
    path = str(tmp_path / "in")
    rows = [(1, 2, "2024-01-01 00:00:00"), (2, 3, "2024-01-01 00:00:30"), (1, 3, "2024-01-01 00:00:50"), (1, 9, "2024-01-01 00:00:10"), (2, 9, "2024-01-01 02:00:00")]
    spark.createDataFrame(rows, "src long, dst long, at string").select("src", "dst", F.to_timestamp("at").alias("ts")).orderBy("ts").coalesce(1).write.parquet(path)
    edges = spark.readStream.schema("src long, dst long, ts timestamp").parquet(path).withWatermark("ts", "1 minute").withColumn("rk", F.lit(0).cast("long"))
    with_ttl = st.run_to_table(st.new_triangles(edges, 1, "60"), "forgetting", "append", str(tmp_path / "c"))
    assert with_ttl.count() == 0  # the newest edge makes all others too old
    kept = st.run_to_table(st.new_triangles(edges, 1, "86400"), "remembering", "append", str(tmp_path / "d"))
    assert sorted(tuple(r)[1:] for r in kept.collect()) == [(1, 2, 3), (1, 2, 9)]


def test_late_rows_are_counted(spark, sf, tmp_path):
    members = st.hourly_members(st.event_stream(spark, sf))
    assert st.run_to_folder(members, str(tmp_path / "o"), str(tmp_path / "c")) == 0
    early = str(tmp_path / "in")
    for i, at in enumerate(("2024-01-05 00:00:00", "2024-01-06 00:00:00", "2024-01-01 00:00:00")):
        spark.createDataFrame([(i, i, "purchase", at)], "event_id long, user_id long, event_type string, at string").select("event_id", "user_id", "event_type", F.to_timestamp("at").alias("ts")).coalesce(1).write.mode("append").parquet(early)
        stream = spark.readStream.schema("event_id long, user_id long, event_type string, ts timestamp").parquet(early)
        late = st.run_to_folder(st.hourly_members(stream), str(tmp_path / "p"), str(tmp_path / "q"))
    assert late == 1


def test_asof_and_numbers(spark):
    left = spark.createDataFrame([(1, "a", 5), (2, "a", 9), (3, "b", 5), (4, "a", 1)], "id long, k string, t long")
    right = spark.createDataFrame([("a", 2, "x"), ("a", 5, "y"), ("a", 5, "z"), ("b", 6, "w")], "k string, t long, v string")
    got = {r["id"]: (r["last_t"], r["last_v"]) for r in relational.asof_join(left, right, ["k"], "t", ["v"]).collect()}
    assert got == {1: (5, "z"), 2: (5, "z"), 3: (None, None), 4: (None, None)}
    numbers = relational.numbered(spark.range(1000).select((F.col("id") * 7 % 1000).alias("v")), ["v"], parts=7)
    assert numbers.where("v <> number").count() == 0 and numbers.count() == 1000


def test_near_docs(spark):
    line, other = "x" * 80, "y" * 90
    docs = spark.createDataFrame([(5, f"a\n{line}"), (3, line), (9, f"{line}\n{other}"), (7, other), (8, "short\nlines"), (None, line), (4, None)], "doc_id long, text string")
    assert sorted(map(tuple, graphs.near_docs(docs).collect())) == [(3, 5), (3, 9), (7, 9)]
