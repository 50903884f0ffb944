"""Streams over several micro-batches: late rows, repeats, state across batches, upkeep of an index."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from lookalike.streaming import features as S

T0 = dt.datetime(2024, 1, 1, 8)


def event(i, minutes, user=1, kind="view", value=1.0):
    return (i, T0 + dt.timedelta(minutes=minutes), user, kind, value, "{}")


@pytest.fixture
def feed(spark, tmp_path):
    """Writes batches as files in order and reads them one per micro-batch."""

    def make(*batches):
        for n, rows in enumerate(batches):
            spark.createDataFrame(rows, S.EVENTS).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
            for p in (tmp_path / "in").glob("part-*.parquet"):
                if not p.name.startswith("part-b"):
                    p.rename(p.with_name(f"part-b{n}.parquet"))
        import os

        for n in range(len(batches)):  # the source takes files by time
            os.utime(tmp_path / "in" / f"part-b{n}.parquet", (1_700_000_000 + n * 100,) * 2)
        return spark.readStream.schema(S.EVENTS).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))

    return make


def test_late_rows_are_dropped(feed):
    """Two batches after 14:00 was seen with two hours of patience, a row of 8:30 is too late; one of 13:00 is not."""
    s = feed([event(1, 10), event(2, 360)], [event(7, 361)], [event(3, 30), event(4, 300)], [event(5, 900)], [event(6, 901)])
    got = {r["start"]: r["n"] for r in S.drain(S.tumbling(s)).collect()}
    assert got == {T0: 1, T0 + dt.timedelta(hours=5): 1, T0 + dt.timedelta(hours=6): 2}


def test_repeats_across_batches(feed):
    s = feed([event(1, 0), event(1, 0)], [event(1, 1), event(2, 2)])
    assert sorted(r["event_id"] for r in S.drain(S.deduped(s)).collect()) == [1, 2]


def test_running_verdicts_keep_state(feed):
    s = feed([event(1, 0, kind="view"), event(2, 1, kind="buy")], [event(3, 2, kind="view"), event(4, 3, user=2, kind="buy")])
    got = [(r["user_id"], r["before"], r["after"]) for r in S.drain(S.verdict_changes(s)).orderBy("user_id", "ts").collect()]
    assert got == [(1, None, "view"), (1, "view", "buy"), (1, "buy", "view"), (2, None, "buy")]


def test_running_verdicts_equal_a_plain_count(feed):
    """Ties, repeats and more events than are counted at a time; events without a type count for nothing."""
    n = S.COUNTED_ROWS + 500
    kinds = [None if i % 50 == 49 else "abc"[(i * i + i // 7) % 3] for i in range(n)]
    rows = [event(i, i, kind=k) for i, k in enumerate(kinds)]
    counts, verdict, want = {}, None, []
    for k in filter(None, kinds):
        counts[k] = counts.get(k, 0) + 1
        now = min(counts, key=lambda t: (-counts[t], t))
        if now != verdict:
            want.append((verdict, now))
            verdict = now
    got = S.drain(S.verdict_changes(feed(rows[: n // 3], rows[n // 3 :]))).orderBy("ts").collect()
    assert [(r["before"], r["after"]) for r in got] == want and len(want) > 3


def test_idle_users_are_forgotten(feed):
    """User 1 is silent for days: the state goes, and the next event is a first one again."""
    s = feed([event(1, 0, kind="a"), event(2, 1, kind="a", user=2)], [event(3, 5000, kind="b", user=2)], [event(4, 5001, kind="b", user=2)], [event(5, 5002, kind="b", user=1)])
    got = [(r["user_id"], r["before"], r["after"]) for r in S.drain(S.verdict_changes(s, forget="1 day")).orderBy("user_id", "ts").collect()]
    assert got[:2] == [(1, None, "a"), (1, None, "b")]


def test_twin_feed_meets_across_batches(feed):
    s = feed([event(1, 0, user=1)], [event(2, 20, user=2), event(3, 40, user=3), event(4, 10, user=4, kind="buy")])
    assert sorted(tuple(r) for r in S.drain(S.twin_feed(s)).select("a_id", "b_id").collect()) == [(1, 2), (2, 3)]


def test_sessions(feed):
    s = feed([event(1, 0), event(2, 300), event(3, 700)])
    got = sorted((r["start"], r["n"]) for r in S.drain(S.sessions(s), "complete").collect())
    assert got == [(T0, 2), (T0 + dt.timedelta(minutes=700), 1)]


def test_upkeep_and_drift(spark, tmp_path):
    from lookalike.operators import cluster
    from lookalike.operators.cluster import LayerSpec

    nodes = spark.range(40).select(F.col("id").alias("node_id"), F.lit(0).alias("verdict"), F.array(F.cos(F.col("id").cast("double")), F.sin(F.col("id").cast("double"))).alias("sig"))
    layers = cluster.build_layers(nodes, LayerSpec(p=2, m=4, rounds=3))
    nodes.repartition(4).write.parquet(str(tmp_path / "arrivals"))
    stream = spark.readStream.schema(nodes.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "arrivals"))
    got = S.upkeep(stream, layers, str(tmp_path / "index"))
    want = S.choose_home(S.assign(nodes, layers), layers)
    cols = ["node_id", "layer", "cluster"]
    assert sorted(map(tuple, got.select(cols).collect())) == sorted(map(tuple, want.select(cols).collect()))
    d = S.drift(want, got).head()
    assert d["base"] == pytest.approx(d["arrived"])
