"""Cases that the second round's review found."""

import duckdb
import pytest

import __spark_entry__ as entry
from test_oracle import rows


def same(spark, name, folder, *tables):
    """The query's rows, after a comparison with its SQL over tables of folder."""
    con = duckdb.connect()
    for t in tables:
        con.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
    df, rel = entry.queries()[name](spark, str(folder)), con.sql(entry.oracle_sql()[name])
    found = rows(df.columns, df.collect())
    assert found == rows(rel.columns, rel.fetchall())
    return found


@pytest.mark.parametrize("last", ["00:59:59.6", "00:59:59.5", "00:59:59.499", "01:00:00.4"])
@pytest.mark.parametrize("name", ["s_window_tumbling", "s_window_sliding"])
def test_windows_close_at_the_rounded_last_time(spark, tmp_path, name, last):
    """An event in the hour that ends one day before the last time, to the second."""
    values = f"(0, timestamp '2024-01-02 00:10:00', 7, 'view', 1.5::double, '{{}}'), (1, timestamp '2024-01-03 {last}', 8, 'view', 2.5::double, '{{}}')"
    duckdb.sql(f"copy (select * from (values {values}) t(event_id, ts, user_id, event_type, value, props)) to '{tmp_path}/events.parquet'")
    assert len(same(spark, name, tmp_path, "events")) == (last != "00:59:59.499")


def test_sliding_windows_count_distinct_users(spark, tmp_path):
    """A user twice in an hour, again in a later hour of the same windows, a second user, a null user and null values."""
    at = [("01:10", 7, 1.5), ("01:50", 7, 2.5), ("03:00", 7, "null"), ("03:30", 9, 4.25), ("04:30", "null", 1.0), ("09:30", "null", "null")]
    values = ", ".join(f"({k}, timestamp '2024-01-02 {t}:00', {u}, 'view', {v}, '{{}}')" for k, (t, u, v) in enumerate([*at, ("23:59", 8, 0.5)]))
    values += ", (99, timestamp '2024-01-04 12:00:00', 8, 'view', 0.5, '{}')"
    duckdb.sql(f"copy (select event_id::bigint as event_id, ts, user_id::bigint as user_id, event_type, value::double as value, props from (values {values}) t(event_id, ts, user_id, event_type, value, props)) to '{tmp_path}/events.parquet'")
    same(spark, "s_window_sliding", tmp_path, "events")
    day = 1_704_153_600
    found = {(r.start - day) // 3600: r.n_users for r in entry.queries()["s_window_sliding"](spark, str(tmp_path)).collect()}
    assert found == dict.fromkeys([-4, -3, *range(18, 24)], 1) | dict.fromkeys(range(-2, 4), 2) | dict.fromkeys(range(4, 10), 0)


def test_entropy_of_groups_of_ids(spark, tmp_path):
    """Many ids in a group, two groups, a null id, a null quantity, and an id with nulls alone."""
    values = ", ".join(f"({k}, {q})" for k, q in [(1, 3.0), (1, 5.0), (2, 7.0), (4095, 1.0), (4095, "null"), (4095, 1.0), (4096, 2.0), (4097, "null"), ("null", 1.0), ("null", 3.0)])
    duckdb.sql(f"copy (select k::bigint as l_orderkey, q::double as l_quantity from (values {values}) t(k, q)) to '{tmp_path}/lineitem.parquet'")
    assert len(same(spark, "u_apply_in_pandas", tmp_path, "lineitem")) == 6


def test_whole_rounds_stay_a_chain(toy, monkeypatch):
    """States are written every few rounds, not in each half round."""
    from hgengine import runtime
    from hgengine.algorithms import labels

    written = []
    monkeypatch.setattr(runtime, "cut", lambda df, cut=runtime.cut: written.append(1) or cut(df))
    for rule in ("min",):
        for rounds in (1, 2):
            whole, changed = (sorted(labels.run(toy, rounds, until_stable=stable, rule=rule).frame.vertices.select("vid", "label").collect()) for stable in (False, True))
            assert whole == changed
        written.clear()
        labels.run(toy, 5, until_stable=False, rule=rule)
        assert len(written) == 2


def test_ranks_on_pairs_keep_no_pairs(toy, monkeypatch):
    from hgengine import pairwise
    from hgengine.algorithms import pagerank

    monkeypatch.setattr(pairwise, "to_pairwise", lambda *a, **k: pytest.fail("pairs were made to be kept"))
    exact = {r.vid: r.rank for r in pagerank.pagerank(toy, max_rounds=3).vertices.collect()}
    for few in (pairwise.FEW_STATES, 0):
        monkeypatch.setattr(pairwise, "FEW_STATES", few)
        assert {r.vid: r.rank for r in pairwise.pagerank_pairwise(toy, max_rounds=3).collect()} == pytest.approx(exact, abs=1e-12)


def test_recursion_reads_its_table(spark, tmp_path):
    duckdb.sql(f"copy (select n::int as l_linenumber from (values (1), (1), (2), (3), (3), (3), (5)) t(n)) to '{tmp_path}/lineitem.parquet'")
    assert len(same(spark, "o_cte_recursive", tmp_path, "lineitem")) == 3


def test_data_source_serves_a_table(spark, tmp_path):
    duckdb.sql(f"copy (select k as l_orderkey, v as l_partkey from (values (1::bigint, 7::bigint), (1, 7), (2, 7), (2, 9), (3, 8)) t(k, v)) to '{tmp_path}/lineitem.parquet'")
    assert len(same(spark, "u_data_source", tmp_path, "lineitem")) == 3
