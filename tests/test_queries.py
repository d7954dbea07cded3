"""Registered queries against DuckDB, a sample of each kind, and the shape of some plans."""

import duckdb
import pytest

import __spark_entry__ as entry

DIR = "/root/testdata/sf0.001"
KEYS = [
    "m_blocks_A", "m_blocks_D", "m_edges_D", "m_related_D", "m_copy_scores_D", "m_merge_scores_D", "m_two_way_best_A", "m_inflation_D", "m_mandatory_D", "x_oracle_sa_C", "x_qa_exclusive_D",
    "w_single_D", "w_multi_weighted_D", "search_exact_A", "search_units_sweep_D", "search_coordinated_D", "search_leaks_D", "join_asof_grant", "join_interval_validity", "agg_cube", "win_range_frame_time",
    "w_single_E", "search_exact_C", "search_exact_E", "search_units_sweep_E", "search_coordinated_C", "m_maintain_blocks_A", "m_crossover_A", "sample_hash", "sample_strata", "sink_bucketed", "sink_append", "sink_overwrite_partitions", "udtf_topk", "vec_cosine", "scan_partitioned_layout", "stream_tumbling", "stream_policy_apply", "udtf_partitions",
]


def rows(frame):
    frame = frame[sorted(frame.columns)]
    return sorted(tuple("" if v is None or v != v else repr(float(v)) if isinstance(v, float) else str(v) for v in r) for r in frame.astype(object).itertuples(index=False))


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    c.execute("SET TimeZone='UTC'")
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    return c


@pytest.mark.parametrize("key", KEYS)
def test_matches_duckdb(spark, con, key):
    got, want = entry.queries()[key](spark, DIR).toPandas(), con.execute(entry.oracle_sql()[key]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_entry_runs(spark):
    out = entry.entry(spark)
    assert out.columns == ["qid", "rank", "vec_id", "dist"] and out.count() > 0


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def plan(df):
    return df._jdf.queryExecution().toString()


def test_block_sizes_do_not_read_vectors(spark):
    from rolelattice.core_queries import ob, tags_of

    assert "embedding:array" not in plan(ob.exclusive_blocks(tags_of(spark, DIR, "D")))


def test_filters_reach_the_scan(spark):
    text = plan(entry.queries()["scan_parquet_pruned"](spark, DIR))
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in text and "l_tax" not in text.split("== Physical Plan ==")[1]


def test_streams_leave_their_rows_in_files(spark, con):
    """The driver holds no rows of a stream's result, which may be as many as the events."""
    for key in ("stream_session", "stream_dedup", "stream_sliding"):
        got = entry.queries()[key](spark, DIR)
        assert "MemoryPlan" not in plan(got) and got.inputFiles()
        assert rows(got.toPandas()) == rows(con.execute(entry.oracle_sql()[key]).df())


def test_toy_layouts_read_the_line_items(spark, con):
    key = "m_toy_layouts"
    assert "lineitem" in entry.oracle_sql()[key]
    assert rows(entry.queries()[key](spark, DIR).toPandas()) == rows(con.execute(entry.oracle_sql()[key]).df())


@pytest.mark.parametrize("key", ["range_rows", "udtf_partitions"])
def test_rows_come_from_a_table(spark, con, key):
    got = entry.queries()[key](spark, DIR)
    assert got.inputFiles()
    assert rows(got.toPandas()) == rows(con.execute(entry.oracle_sql()[key]).df())
