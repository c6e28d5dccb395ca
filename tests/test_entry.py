"""The driver's contract, and every core query against its SQL on the smallest tables."""

import sys

import duckdb
import pytest
from conftest import SF

import __spark_entry__ as entry

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUICK = ["exact_types", "phase_split", "domain_sample", "encode_example", "onehot_state", "onehot_estimate", "gather_estimate", "hadamard_butterfly_estimate", "pooled_lh_estimate", "countsketch_median_estimate", "countmin_bound", "boundary_ties", "boundary_empty", "split_state", "split_estimate_pooled", "split_strict_estimate", "error_cube", "sse_curve", "theory_variance", "privacy_ratio", "space_table", "daily_sketch", "sliding_sketch", "asof_version", "range_join", "moving_count", "segment_report", "two_round_heavy_hitters", "bloom_bits_estimate", "own_hash_estimate"]


def canon(frame):
    cols = sorted(frame.columns)
    return cols, sorted(repr([x.item() if hasattr(x, "item") else x for x in row]) for row in frame[cols].itertuples(index=False))


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in NAMES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def test_entry(spark):
    df = entry.entry(spark)
    assert df.count() == 200 and set(df.columns) == {"item", "f_hat", "path"}


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_sql(spark, con, name):
    assert canon(entry.queries()[name](spark, SF).toPandas()) == canon(con.execute(entry.oracle_sql()[name]).df())


def test_core_does_not_import_the_training_data_operators():
    import subprocess

    code = "import sys, privfreq.workloads.queries; assert not [m for m in sys.modules if m.startswith('privfreq.llm')]"
    subprocess.run([sys.executable, "-c", code], check=True, cwd=entry.__file__.rsplit("/", 1)[0])
