"""Every registered query with SQL agrees with it on the smallest tables; the rest of the package stands alone."""

import subprocess
import sys

import pytest

from tests.conftest import rows_match

KEYS = [
    "corpus_statistics", "monthly_snapshot", "changed_files_half", "byte_budget_sample", "gray_tiles", "word_token_stats", "chunk_plan_stream",
    "sliding_plan", "adaptive_chunked", "adaptive_sliding", "order0_bits", "backoff_pushdown", "cdf_slots", "cached_bits", "robustness_gap",
    "projected_rank", "tokenizer_table", "printed_table_checks", "printed_rank_agreement", "png_filter_cost", "rice_choice", "arrow_score",
    "cogroup_score", "asof_version", "stream_daily_rate", "format_round_trip", "partitioned_slices", "bucketed_model", "provenance", "source_chunks",
    "observed_scan", "rollup_rates", "cube_rates", "vocabulary_maps", "multiset_words", "same_cutoff_pairs", "hinted_joins", "restricted_law",
    "length_auc", "stream_state_bits", "table4_ranks", "context_size_table", "unbroken_bits", "adaptive_order1",
    "pcm_series", "flac_fixed_residuals", "contamination_probe",
]


@pytest.mark.parametrize("key", KEYS)
def test_query_equals_sql(spark, sf, duck, key):
    from slicecode.plans import registry

    rows_match(registry.queries()[key](spark, sf), duck.sql(registry.oracle_sql()[key]))


def test_pushdown_equals_positions(spark, sf):
    from slicecode.plans import registry

    q = registry.queries()
    assert sorted(map(tuple, q["backoff_bits"](spark, sf).collect())) == sorted(map(tuple, q["backoff_pushdown"](spark, sf).collect()))


def test_entry_without_corpus_operators(tmp_path):
    """The entry imports and lists its queries when the corpus subpackage and the pipeline are gone."""
    import os
    import shutil

    here = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{here}/slicecode", tmp_path / "slicecode", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{here}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'robustness_gap' in q and not any(k.startswith('op') and k[2].isdigit() for k in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})


def test_plans(spark, sf):
    """Filters and columns reach the scan; no cross product; the relational path has no Python."""
    from slicecode.plans import registry

    q = registry.queries()
    plan = q["front_page_semi"](spark, sf)._jdf.queryExecution().toString()
    assert "PushedFilters" in plan and "quality" in plan and "text" not in plan.split("Physical Plan")[1].split("ReadSchema: ")[1].split("\n")[0]
    for key in ("backoff_pushdown", "robustness_gap"):
        plan = q[key](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "Python" not in plan and "Arrow" not in plan
