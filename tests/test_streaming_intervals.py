from motifscan.sources.tables import load
from motifscan.streaming import edges as st


def test_interval_pairs_match_a_batch_join(spark, sf, tmp_path):
    got = st.run_to_table(st.interval_pairs(st.event_stream(spark, sf)), "near_pairs", "append", str(tmp_path / "p")).count()
    e = load(spark, sf, "events").where("event_type = 'purchase'").select("user_id", "ts")
    a, b = e.toDF("src", "ts"), e.toDF("dst", "ts2")
    assert got == a.join(b).where("src < dst and ts2 >= ts - interval 10 minutes and ts2 <= ts + interval 10 minutes").count() > 0


def test_batches_of_edges(spark, sf, tmp_path):
    events = st.without_repeats(st.event_stream(spark, sf))
    assert st.run_to_table(events, "once", "append", str(tmp_path / "d")).count() == load(spark, sf, "events").count()
    st.append_edges(st.hourly_members(st.event_stream(spark, sf)), str(tmp_path / "e"), str(tmp_path / "c"))
    got = spark.read.parquet(str(tmp_path / "e")).select("src", "dst").distinct().count()
    from motifscan.sources import graphs

    assert 0 < got <= graphs.coactive_purchase(spark, sf).edges.count()  # the last window stays open
