import os
import random

import pytest

from helpers import duck, same
from pyspark.sql import functions as F
from trianglestream.operators.kernels import simulate
from trianglestream.operators.mapping import GreedyColours
from trianglestream.plans import catalog
from trianglestream.streaming.edges import activity_sessions, clean_stream, edge_counts, edge_files, edge_rate
from trianglestream.streaming.routed import AdaptiveMaster, estimate_adaptive_stream, estimate_stream, run_to_end, settle, stream_events


def stored(spark, path, n=150, files=3):
    pairs = [(a, b) for a in range(18) for b in range(a + 1, 18)]
    random.Random(3).shuffle(pairs)
    rows = [(t, u, v) for t, (u, v) in enumerate(pairs[:n], 1)]
    df = spark.createDataFrame(rows, "t bigint, u bigint, v bigint").select(F.timestamp_seconds("t").alias("ts"), "u", "v")
    for i in range(files):
        part = df.where((F.unix_timestamp("ts") - 1) % 1 == 0).where((F.unix_timestamp("ts") > n * i // files) & (F.unix_timestamp("ts") <= n * (i + 1) // files))
        part.coalesce(1).write.mode("append").parquet(path)
    return rows


def test_stream_equals_kernel_and_survives_restart(spark, tmp_path):
    src = str(tmp_path / "edges")
    rows = stored(spark, src)
    k, b = 3, 20
    hits, num = simulate(rows, k, b, lambda x: x % k, seed=5)
    want = {(-1 if n is None else n): hits[n] + num[n] / (b * (b - 1)) for n in hits}
    for lazy in (False, True):
        out, check = str(tmp_path / f"out{lazy}"), str(tmp_path / f"check{lazy}")
        updates = estimate_stream(edge_files(spark, src), k, b, seed=5, lazy=lazy)
        got = {r["node"]: r["est"] for r in settle(run_to_end(updates, out, check), b).collect()}
        assert got.keys() == want.keys() and all(abs(got[n] - want[n]) < 1e-9 for n in want)
        # A second start from the same checkpoint finds nothing new and changes nothing.
        again = {r["node"]: r["est"] for r in settle(run_to_end(estimate_stream(edge_files(spark, src), k, b, seed=5, lazy=lazy), out, check), b).collect()}
        assert again == got


def test_clean_windows_and_sessions(spark, tmp_path):
    src = str(tmp_path / "raw")
    spark.createDataFrame([(10, 2, 1), (11, 1, 2), (12, 3, 3), (5000, 1, 4)], "t bigint, u bigint, v bigint").select(F.timestamp_seconds("t").alias("ts"), "u", "v").coalesce(1).write.parquet(src)
    for name, df, want in (
        ("clean", clean_stream(edge_files(spark, src)).select("u", "v"), {(1, 2), (1, 4)}),
        ("counts", edge_counts(edge_files(spark, src)).select("edges"), {(3,), (1,)}),
    ):
        df.writeStream.format("memory").queryName(f"t_{name}").outputMode("append" if name == "clean" else "complete").trigger(availableNow=True).start().awaitTermination()
        assert {tuple(r) for r in spark.table(f"t_{name}").collect()} == want
    sessions = activity_sessions(spark.read.parquet(src))
    assert sessions.where("node = 1").count() == 2


def test_adaptive_batches_match_one_pass(spark, tmp_path):
    rows = stored(spark, str(tmp_path / "e"), 60)
    df = spark.createDataFrame(rows, "t bigint, u bigint, v bigint").select(F.timestamp_seconds("t").alias("ts"), "u", "v")
    master = AdaptiveMaster(3)
    for a, b in ((0, 20), (20, 60)):
        master.colour_batch(df.where((F.unix_timestamp("ts") > a) & (F.unix_timestamp("ts") <= b))).count()
    whole = AdaptiveMaster(3)
    whole.colour_batch(df)
    assert master.state.colour == whole.state.colour


def test_events_become_files(spark, tmp_path):
    path = stream_events(spark, "/root/testdata/sf0.001", str(tmp_path / "ev"))
    assert spark.read.parquet(path).count() == 105


def test_event_files_were_written_in_order_of_time(spark, tmp_path):
    """A file stream takes files by their time of modification, so it must follow the events' own time."""
    path = stream_events(spark, "/root/testdata/sf0.01", str(tmp_path / "ev"))
    files = sorted((f for f in (tmp_path / "ev").iterdir() if f.name.endswith(".parquet")), key=lambda f: f.stat().st_mtime_ns)
    spans = [spark.read.parquet(str(f)).agg(F.min("ts"), F.max("ts")).first() for f in files]
    assert len(files) == 6 and all(a[1] < b[0] for a, b in zip(spans, spans[1:]))


def test_adaptive_stream_equals_kernel_across_an_interruption(spark, tmp_path):
    """The third file comes only after a first run ended; both queries go on from their checkpoints."""
    import shutil

    src, held = str(tmp_path / "edges"), str(tmp_path / "later")
    rows = stored(spark, src)
    files = sorted((f for f in (tmp_path / "edges").iterdir() if f.name.endswith(".parquet")), key=lambda f: spark.read.parquet(str(f)).agg(F.min("ts")).first()[0])
    (tmp_path / "later").mkdir()
    shutil.move(str(files[2]), held)
    colours = GreedyColours(3, 0.2)
    for _, u, v in rows:
        colours.see(u, v)
    hits, num = simulate(rows, 3, 20, lambda x: colours.colour[x], seed=5)
    want = {(-1 if n is None else n): hits[n] + num[n] / (20 * 19) for n in hits}
    for again in (False, True):
        if again:
            shutil.move(f"{held}/{files[2].name}", src)
        updates = estimate_adaptive_stream(edge_files(spark, src), 3, 20, str(tmp_path / "routed"), str(tmp_path / "state"), seed=5)
        got = {r["node"]: r["est"] for r in settle(run_to_end(updates, str(tmp_path / "out"), str(tmp_path / "state")), 20).collect()}
        assert (got.keys() == want.keys() and all(abs(got[n] - want[n]) < 1e-9 for n in want)) == again


def test_rate_source_makes_edges(spark):
    stream = edge_rate(spark, 50, 100)
    assert stream.isStreaming and stream.columns == ["ts", "u", "v"]


@pytest.mark.parametrize("name", ["streaming_routed_eager_coactivity", "streaming_routed_lazy_coactivity", "streaming_adaptive_coactivity"])
def test_batches_follow_the_events_whatever_the_files_times_say(spark, monkeypatch, name):
    """A store may give files other times of modification than the order in which they were written."""
    from trianglestream.streaming import scenarios

    def turned(spark, path, *options):
        folder = path.removeprefix("file://")
        files = [f"{folder}/{f}" for f in os.listdir(folder) if f.endswith(".parquet")]
        for f in files:
            first = spark.read.parquet(f).agg(F.min(F.unix_timestamp("ts"))).first()[0] or 0
            os.utime(f, (1_700_000_000 - first, 1_700_000_000 - first))
        return edge_files(spark, path, *options)

    monkeypatch.setattr(scenarios, "edge_files", turned)
    sf = "/root/testdata/sf0.01"  # samples of the smaller tables hold all edges, in any order
    assert same(catalog.queries()[name](spark, sf), duck(sf), catalog.oracle_sql()[name])
