"""Streams give what the batch gives."""

from pyspark.sql import functions as F

from freeseg.functions import kernels, udfs
from freeseg.operators import apply, model, segment
from freeseg.sources import corpus
from freeseg.streaming import streams


def test_counts_of_three_batches_equal_the_batch(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang", "text")
    docs.repartition(3).write.parquet(str(tmp_path / "d"))
    lines = corpus.lines(streams.file_stream(spark, str(tmp_path / "d")).select("lang", "text"), "text", "lang")
    got = streams.finished(streams.count_stream(lines, 2), "complete")
    want = model.count_grams(corpus.lines(docs, "text", "lang"), 2)
    assert got.select(*want.columns).exceptAll(want).isEmpty() and got.count() == want.count()


def test_segmented_stream(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang", "text").where("length(text) < 2000")
    docs.write.parquet(str(tmp_path / "d"))
    slices = udfs.freedom_slices(model.count_grams(corpus.train_lines(spark, sf), 2), segment.Config())
    got = streams.finished(streams.segment_stream(streams.file_stream(spark, str(tmp_path / "d")), slices), "append")
    want = apply.segment_texts(docs, slices)
    assert got.count() == want.count() and want.exceptAll(got.select(*want.columns)).isEmpty()


EVENTS = "event_id long, ts string, user_id long, event_type string"


def events(spark, rows):
    return spark.createDataFrame(rows, EVENTS).withColumn("ts", F.to_timestamp("ts"))


def test_late_rows_are_dropped(spark):
    day = "2024-01-01 "
    files = [
        [(1, day + "10:00:00", 1, "view"), (2, day + "20:00:00", 1, "view")],
        [(3, day + "21:30:00", 1, "view"), (4, day + "20:10:00", 1, "view")],
        [(5, day + "10:30:00", 1, "view"), (6, day + "20:50:00", 1, "buy"), (7, "2024-01-02 10:00:00", 1, "view")],
    ]
    out = streams.run_windows(spark, [events(spark, f) for f in files])
    got = {(r.at, r.event_type): r.n for r in out.select(F.timestamp_seconds("begins").cast("string").alias("at"), "event_type", "n").collect()}
    # The third file's 10:30 is later than the watermark of the first two and is dropped; its 20:50 is not; the last window is still open.
    assert got == {(day + "10:00:00", "view"): 1, (day + "20:00:00", "view"): 2, (day + "20:00:00", "buy"): 1, (day + "21:00:00", "view"): 1}


def test_sessions_and_duplicates(spark, tmp_path):
    rows = [(1, "2024-01-01 10:00:00", 1, "view"), (1, "2024-01-01 10:00:00", 1, "view"), (2, "2024-01-01 10:30:00", 1, "buy"), (3, "2024-01-01 15:00:00", 1, "view"), (4, "2024-01-03 00:00:00", 2, "view")]
    events(spark, rows).coalesce(1).write.parquet(str(tmp_path / "e"))
    one = streams.finished(streams.deduplicated(streams.file_stream(spark, str(tmp_path / "e"))), "append")
    assert sorted(r.event_id for r in one.collect()) == [1, 2, 3, 4]
    sessions = streams.finished(streams.session_counts(streams.file_stream(spark, str(tmp_path / "e"))), "append")
    assert sorted((r.user_id, r.n) for r in sessions.collect()) == [(1, 1), (1, 3)]
    toks = streams.session_tokens(events(spark, rows))
    by = {r.stmt_id.split(":")[0] + r.stmt_id[-4:]: r.t for r in toks.groupBy("stmt_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("tok_no", "token"))), lambda x: x["token"]), "").alias("t")).collect()}
    assert sorted(by.values()) == ["v", "v", "vvb"]


def plain_segments(symbols, freedom, threshold=0.4):
    top, held, total, out = max(freedom.values()), "", 0.0, []
    for n, s in enumerate(symbols, 1):
        v = freedom.get(s, 0) / top
        total += v
        held += s
        if v - total / n > threshold:
            out.append(held)
            held = ""
    return out, held


def test_stateful_segments_do_not_depend_on_batches(spark, sf, tmp_path):
    freedom = dict(zip("cpvsa", [3, 2, 5, 1, 4], strict=True))
    own = kernels.make_slice(list(freedom), list(freedom.values()), [1] * 5)
    rows = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    last = rows.agg(F.max("ts")).first()[0]
    end = rows.limit(1).select(F.lit(-1).cast("long").alias("event_id"), (F.lit(last) + F.expr("INTERVAL 9 DAY")).alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit("view").alias("event_type"))
    want = {}
    for r in rows.orderBy("ts", "event_id").collect():
        want.setdefault(r.user_id, []).append(r.event_type[0])
    got = []
    for k, cuts in enumerate((1, 4)):
        to = str(tmp_path / str(k))
        times = sorted(r.ts for r in rows.select("ts").collect())
        edges = [times[0], *(times[len(times) * j // cuts] for j in range(1, cuts)), None]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            part = rows.where((F.col("ts") >= a) & (F.lit(b is None) | (F.col("ts") < (b or a)))).select("event_id", "ts", "user_id", "event_type")
            part.orderBy(F.rand(3)).coalesce(1).write.mode("append").parquet(to)
        for j in range(2):  # these move the watermark past all others
            end.withColumn("ts", F.col("ts") + F.expr(f"INTERVAL {9 * j} DAY")).coalesce(1).write.mode("append").parquet(to)
        out = streams.finished(streams.stateful_segments(streams.file_stream(spark, to), own, idle="900 days"), "append")
        found = {}
        for r in out.where("user_id >= 0").collect():
            found.setdefault(r.user_id, []).append(r.token)
        got.append({user: sorted(toks) for user, toks in found.items()})
    assert got[0] == got[1]
    for user, symbols in want.items():
        assert got[0].get(user, []) == sorted(plain_segments(symbols, freedom)[0])


def test_idle_users_are_closed_and_forgotten(spark, tmp_path):
    own = kernels.make_slice(["v"], [1], [1])
    day = "2024-01-0{} 10:00:00"
    for d in (1, 4, 7, 9):
        events(spark, [(d, day.format(d), 1 if d == 1 else 2, "view")]).coalesce(1).write.mode("append").parquet(str(tmp_path / "e"))
    out = streams.finished(streams.stateful_segments(streams.file_stream(spark, str(tmp_path / "e")), own, threshold=9.0), "append")
    assert [(r.user_id, r.token) for r in out.where("user_id = 1").collect()] == [(1, "v")]


def test_udfs(spark, sf):
    grams = model.count_grams(corpus.train_lines(spark, sf), 2)
    udfs.register(spark, grams)
    udfs.register_tables(spark)
    assert spark.sql("select bag_f1(h, r) f from values ('a', 'a'), ('b', 'a') t(h, r)").first().f == 0.5
    assert spark.sql("select segment_text('en', null) t").first().t is None
    toks = [r.token for r in spark.sql("select token from text_tokens('ab ab cb ab', 0.4) order by tok_no").collect()]
    assert "".join(toks) == "ab ab cb ab"
