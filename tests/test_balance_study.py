"""The balance study on the events table."""

import numpy as np

from axisgrove import comparison
from axisgrove.sources.tables import table

SF = "/root/testdata/sf0.001"


def test_every_event_is_in_a_minute(spark):
    events = table(spark, SF, "events")
    found = comparison.minutes(events).toPandas()
    rows = events.selectExpr("timestampdiff(MINUTE, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts) AS m", "CAST(round(value * 100) AS bigint) AS v").toPandas().groupby("m")["v"].agg(["sum", "count"])
    assert dict(zip(found.point_id, found.c1, strict=True)) == {m: r["sum"] / r["count"] for m, r in rows.iterrows()}


def test_study_reads_the_table_and_takes_every_point(spark):
    from axisgrove import catalog

    assert catalog.QUERIES["balance_study_order"](spark, SF).inputFiles()
    n = comparison.minutes(table(spark, SF, "events")).count()
    got = comparison.balance_study(table(spark, SF, "events"), slacks=(0.1, 0.5), batches=7).collect()
    assert {(r["stream"], r["slack"]) for r in got} == {(s, a) for s in ("in time", "tenth first", "shuffled") for a in (0.1, 0.5)}
    assert all(r["moved_ratio"] * n > 0.9 * n and r["visits_mean"] > 0 for r in got)


def test_orders_are_permutations():
    at, hashed = np.arange(50)[::-1], np.random.default_rng(2).integers(-99, 99, 50)
    for kind in ("in time", "tenth first", "shuffled"):
        assert sorted(comparison.stream_order(kind, at, hashed)) == list(range(50))
    tenth = comparison.stream_order("tenth first", at, hashed)
    first = int((hashed % 10 == 0).sum())
    assert (hashed[tenth[:first]] % 10 == 0).all() and (np.diff(at[tenth[first:]]) > 0).all()
