"""Every query with SQL against DuckDB on the smallest tables."""

import os

import duckdb
import pytest

from patternspark.plans.queries import build

QUERIES, SQL = build()
#: Same code as a query that is tested, on another database, threshold or setting.
ALIKE = [k for i, k in enumerate(sorted(SQL)) if k.startswith(("itemize_", "profile_", "freq_", "maximal_", "enc_size_", "advisor_", "border_profile_", "w")) and i % 4]
PICK = [k for k in sorted(SQL) if k not in ALIKE]


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        if os.path.exists(f"{sf}/{t}.parquet"):
            c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("key", PICK)
def test_same_rows(spark, sf, duck, key):
    got, want = QUERIES[key](spark, sf).toPandas(), duck.execute(SQL[key]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    plain = lambda d: sorted(map(repr, d[cols].astype(object).where(d[cols].notna(), None).itertuples(index=False, name=None)))
    assert plain(got) == plain(want)


def test_every_query_has_sql_or_a_reason():
    without = {k for k in set(QUERIES) - set(SQL) if not k.endswith("_full")}
    assert without <= {
        "enc_cardinality_seqcounter_illus", "enc_cardinality_bdd_illus", "enc_cardinality_totalizer_illus", "enc_cardinality_network_illus", "opb_illus", "cnf_illus", "freqsat_solve", "maximal_wide_70x200",
        "search_times_order_mix", "blocking_growth_order_mix", "beta_alpha_ratio_order_mix", "restriction_overhead_order_mix", "w07_searches_and_times", "solver_conflicts_order_mix", "plan_cost_order_mix_0_2", "run_cost_order_mix_0_2", "phase_transition_seconds",
    }


#: Queries whose rows came from fixed values before.
READS = [
    "blocking_counts",
    "cnf_illus",
    "coverage_illus",
    "enc_cardinality_bdd_illus",
    "enc_cardinality_network_illus",
    "enc_cardinality_seqcounter_illus",
    "enc_cardinality_totalizer_illus",
    "enc_coverage_rows_illus",
    "enc_frequency_rows_illus",
    "enc_size_clausal_illus",
    "enc_size_positive_illus",
    "enc_size_reduced_illus",
]


@pytest.mark.parametrize("key", READS)
def test_rows_come_from_a_given_table(spark, tmp_path, key):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[key](spark, str(tmp_path)).count()
