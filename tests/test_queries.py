"""Named queries against their SQL, on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from galoislake.streaming import queries

SF = "/root/testdata/sf0.001"
NAMES = ["scale_bands", "scale_related", "derive_objects", "close_objects", "local_closures_conversation_shape", "closure_pairs_document_meta", "context_profile_all", "covers_conversation_shape", "trace_tiny_single", "trace_tiny_all",
         "stream_session_context", "stream_family_session_mix", "stream_common_by_user", "stream_session_windows", "stream_sliding_windows", "concept_test_tiny", "extents_by_parents_tiny", "paths_up_nation_activity", "trace_tiny_every_round", "derive_attributes", "udtf_concepts_by_day", "sql_fn_feasible", "roundtrip_baskets", "sizes_cube", "asof_purchase_view", "extents_nation_region"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for f in os.listdir(SF):
        c.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{f}'")
    return c


def rows(frame, columns):
    short = lambda v: None if v is None or v != v else round(float(v), 9) if isinstance(v, float) else v
    return sorted(repr(tuple(short(v) for v in r)) for r in frame[columns].astype(object).itertuples(index=False, name=None))


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, duck, name):
    got = entry.queries()[name](spark, SF).toPandas()
    want = duck.execute(entry.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got, sorted(got.columns)) == rows(want, sorted(got.columns)) and len(got)


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["intent", "size", "support"] and df.count() == 2305


def test_every_sql_has_its_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_table_function_mines_every_day(spark, tmp_path):
    # (user, day, event type): days far apart, each with its own family
    made = [(1, "2024-01-01", "view"), (1, "2024-01-01", "cart"), (2, "2024-01-01", "view"), (1, "2024-01-17", "cart"), (2, "2024-01-17", "view"), (3, "2025-06-30", "view")]
    events = spark.createDataFrame([(k, u, f"{d} 01:00:00", t, 1.0) for k, (u, d, t) in enumerate(made)], "event_id long, user_id long, ts string, event_type string, value double")
    events.selectExpr("event_id", "user_id", "CAST(ts AS TIMESTAMP) AS ts", "event_type", "value").write.parquet(str(tmp_path / "events.parquet"))
    got = sorted(tuple(r) for r in entry.queries()["udtf_concepts_by_day"](spark, str(tmp_path)).select("day", "intent", "size", "support").collect())
    want = []
    for day in sorted({d for _, d, _ in made}):
        rows = {}
        for k, (u, d, t) in enumerate(made):
            if d == day:
                rows.setdefault(u, set()).update({f"type={t}", "part=0", "v=lo"})
        family = {frozenset().union(*rows.values())}
        for row in rows.values():
            family |= {f & row for f in family}
        want += [(day, ",".join(sorted(f)), len(f), sum(f <= r for r in rows.values())) for f in family]
    assert got == sorted(want)


def made_events(spark, rows):
    frame = spark.createDataFrame([(k, u, ts, t, 1.0, "{}") for k, (u, ts, t) in rows], "event_id long, user_id long, ts string, event_type string, value double, props string")
    return frame.selectExpr("event_id", "user_id", "CAST(ts AS TIMESTAMP_NTZ) AS ts", "event_type", "value", "props")


def test_streams_grow_by_whole_days(spark, tmp_path):
    names = ("part=0", "part=1", "type=cart", "type=view", "v=lo")
    batches = [
        [(0, (1, "2024-01-01 01:00:00", "view")), (1, (2, "2024-01-01 02:00:00", "cart"))],
        [(2, (1, "2024-01-01 07:00:00", "cart")), (2, (1, "2024-01-01 07:00:00", "cart")), (3, (2, "2024-01-02 01:00:00", "view"))],  # the first day goes on; one row is repeated
        [(4, (3, "2024-01-09 01:00:00", "view"))],
        [(7, (3, "2024-01-09 02:00:00", "view"))],  # rows are late by the watermark of the batch before
        [(5, (3, "2024-01-01 08:00:00", "view")), (6, (3, "2024-01-20 01:00:00", "view"))],  # too late by far, and one that closes the rest
    ]
    for k, rows in enumerate(batches):
        made_events(spark, rows).repartition(1).write.parquet(str(tmp_path / "in" / str(k)))
    path = str(tmp_path / "family")
    stream = lambda: queries.events(spark, str(tmp_path / "in"), files_a_batch=1)
    last = queries.grow_family(spark, stream(), names, path)
    got = {r.w0 for r in spark.read.parquet(f"{path}/version={last}").collect()}
    pack = lambda some: sum(1 << 62 - names.index(n) for n in some)
    days = [{"type=view", "type=cart", "part=0", "part=1", "v=lo"}, {"type=cart", "part=0", "v=lo"}, {"type=view", "part=0", "v=lo"}]
    family = {frozenset(names)}
    for d in days:
        family |= {f & d for f in family}
    assert got == {pack(f) for f in family}
    # A second run over the same files writes the same versions again.
    assert queries.grow_family(spark, stream(), names, path) == last
    assert {r.w0 for r in spark.read.parquet(f"{path}/version={last}").collect()} == got
