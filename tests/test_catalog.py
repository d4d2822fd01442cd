"""The catalogue's queries against their SQL on the small tables; a sample by name keeps the run short."""

import duckdb
import pytest

from orderstat import catalog
from orderstat.sources.tables import TABLES

NAMES = ["tail_price", "clusters_price", "ties_returnflag", "fig_example", "fig_buckets", "struct_key_lineitem", "grouped_flags_tail", "cube_flags_median", "gap_sizes", "branch_choice", "weighted_select_price_by_quantity", "baseline_sampled", "trimmed_mean", "iqr_mad", "udtf_pick_ranks", "window_ranks", "rank_error_approx"]


@pytest.mark.parametrize("name", NAMES)
def test_matches_sql(spark, small, name):
    db = duckdb.connect()
    for t in TABLES:
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    got = catalog.QUERIES[name](spark, small)
    run = db.execute(catalog.SQL[name])
    columns = [d[0] for d in run.description]
    assert sorted(columns) == sorted(got.columns)
    norm = lambda rows: sorted(tuple(repr(round(x, 6) if isinstance(x, float) else x) for x in r) for r in rows)
    assert norm(tuple(r[c] for c in columns) for r in got.collect()) == norm(run.fetchall())


def test_stream_matches_batch(spark, small):
    key = lambda r: (str(r["start"])[:10], r["event_type"])
    batch = {key(r): r["value"] for r in catalog.QUERIES["window_ranks"](spark, small).collect()}
    stream = {key(r): r["value"] for r in catalog.QUERIES["stream_window_ranks"](spark, small).collect()}
    assert stream and all(batch[k] == v for k, v in stream.items())
