from datetime import datetime, timedelta

from pyspark.sql import functions as F

from uncertainseq.streaming.events import EVENTS, SessionTables, assembled, read_events, run_sessions, session_numbers, windowed, without_replays

T0 = datetime(2024, 1, 1)


def at(minutes):
    return T0 + timedelta(minutes=minutes)


def put(spark, rows, folder):
    spark.createDataFrame(rows, EVENTS).coalesce(1).write.mode("append").parquet(folder)


def brute_sessions(rows, gap):
    out = {}
    for _, user, ts, _ in sorted(rows, key=lambda r: (r[1], r[2], r[0])):
        held = out.setdefault(user, [])
        if held and ts - held[-1][-1] < timedelta(minutes=gap):
            held[-1].append(ts)
        else:
            held.append([ts])
    return {(user, s[0], s[-1], len(s)) for user, sessions in out.items() for s in sessions}


def test_sessions_of_a_stream_are_those_of_its_rows_with_late_rows_apart(spark, tmp_path):
    source, folder, marks = (str(tmp_path / x) for x in ("in", "out", "marks"))
    batches = [
        [(1, 1, at(0), "a"), (2, 1, at(20), "b"), (3, 2, at(5), "a"), (2, 1, at(20), "b")],
        [(4, 1, at(60), "c"), (2, 1, at(20), "b"), (5, 2, at(100), "a"), (6, 3, at(62), None)],
        [(7, 1, at(95), "x"), (8, 1, at(10), "late"), (9, None, at(99), "nobody"), (10, 3, None, "never")],
        [(11, 4, at(1000), "a")],
        [(12, 4, at(3000), "a")],
    ]
    for rows in batches:
        put(spark, rows, source)
        run_sessions(read_events(spark, source), folder, marks, "30 minutes", "60 minutes").awaitTermination()
    tables = SessionTables(spark, folder)
    late = {r.event_id for r in tables.late().collect()}
    assert late == {8, 9, 10}
    in_time = {r[0]: r for rows in batches for r in rows if r[0] not in late}
    got = [(r.user_id, r.start, r.last, len(r.events)) for r in tables.sessions().collect()]
    want = brute_sessions(in_time.values(), 30)
    assert sorted(got) == sorted(s for s in want if s[2] != at(3000)) and len(got) == len(set(got))
    assert [b for b, _ in tables.marks()] == [0, 1, 2, 3, 4] and tables.marks()[-1][1] == at(3000)


def test_session_numbers_and_odd_rows(spark):
    rows = [(k, k % 3, at(k * k), "a") for k in range(30)] + [(40, 0, at(4), "tie")]
    events = spark.createDataFrame(rows, EVENTS)
    got = {(r.user_id, r.start, r.last, len(r.events)) for r in assembled(session_numbers(events, "30 minutes")).collect()}
    assert got == brute_sessions(rows, 30)
    assert assembled(session_numbers(events.limit(0), "30 minutes")).count() == 0


def test_windows_and_replays_of_a_stream(spark, tmp_path):
    source = str(tmp_path / "in")
    rows = [(k, k % 2, at(7 * k), "a") for k in range(40)]
    put(spark, rows, source)
    put(spark, rows[30:], source)  # replayed
    once = without_replays(read_events(spark, source, 1), "1 day")
    query = once.writeStream.format("memory").queryName("once").trigger(availableNow=True).start()
    query.awaitTermination()
    assert sorted(r.event_id for r in spark.table("once").collect()) == list(range(40))
    plain = spark.createDataFrame(rows, EVENTS)
    for n, (width, slide) in enumerate([("1 hour", None), ("1 hour", "30 minutes")]):
        stream = windowed(without_replays(read_events(spark, source, 1), "1 hour"), width, slide)
        stream.writeStream.outputMode("append").format("memory").queryName(f"w{n}").trigger(availableNow=True).start().awaitTermination()
        batch = windowed(plain, width, slide)
        assert batch.agg(F.sum("n")).first()[0] == 40 * (2 if slide else 1)
        closed = {tuple(r) for r in spark.table(f"w{n}").collect()}
        assert closed and closed <= {tuple(r) for r in batch.collect()}
