"""Registered queries against their DuckDB SQL at the smallest scale; the contract of the entry module."""

import math
import subprocess
import sys

import pytest

import __spark_entry__ as entry
from conftest import SF
from labelflow.queries import methods, relational, streams

SOME = [
    "edges_part_attrs", "weighted_trade_edges", "value_band_edges", "co_activity_edges", "label_as_of_event", "seed_coverage_cube", "top_labels_per_node", "doc_token_edges",
    "cms_update", "cms_point_query", "sizing_table", "dataset_card", "ma_exact_t3", "ma_objective_trace", "ma_dummy_label", "sketch_t3_cells", "sketch_commutes", "sketch_fused_t3",
    "decode_topk", "decode_threshold", "approximation_error", "harmonic_t3", "adsorption_sketch_t3", "community_bound", "controls", "retrieval_measures", "few_labels_curve_t2", "source_classify", "stream_late_drop", "stream_named_events", "stream_interval_edges", "stream_session_totals", "stream_seed_state", "mrr_exact", "mrr_sketch_20x3", "bound_violations", "self_injection_growth", "store_choice", "conductance", "stream_window_cells", "stream_dedup",
]


def plain(rows):
    def value(v):
        if v is None or isinstance(v, float) and math.isnan(v):
            return "null"
        return repr(float(v)) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)

    return sorted(tuple(value(v) for v in r) for r in rows)


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, duck, name):
    df = (relational.Q | methods.Q | streams.Q)[name](spark, SF)
    columns = sorted(df.columns)
    out = duck.sql((relational.SQL | methods.SQL | streams.SQL)[name])
    assert sorted(out.columns) == columns
    got = [tuple(r[c] for c in columns) for r in df.collect()]
    want = [tuple(r[out.columns.index(c)] for c in columns) for r in out.fetchall()]
    assert plain(got) == plain(want)


def test_registry():
    q, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(q) and len(q) > 100
    assert len(sql) > 95


def test_smaller_sketches_lose_accuracy_and_the_prescribed_one_keeps_its_bound(spark):
    value = {n: methods.Q[n](spark, SF).first()["mrr_max"] for n in ("mrr_exact", "mrr_sketch_109x8", "mrr_sketch_20x3")}
    assert value["mrr_exact"] >= value["mrr_sketch_109x8"] > value["mrr_sketch_20x3"]
    assert methods.Q["bound_violations"](spark, SF).first()["violations"] == 0


def test_core_imports_without_the_corpus_operators():
    code = """
import sys
class Absent:
    def find_spec(self, name, path=None, target=None):
        if name in ("corpus_pipeline", "labelflow.llm"):
            raise ModuleNotFoundError(f"No module named '{name}'", name=name)
sys.meta_path.insert(0, Absent())
import __spark_entry__ as e
assert e.llm is None and "ma_exact_t3" in e.queries() and "ma_exact_t3" in e.oracle_sql()
"""
    subprocess.run([sys.executable, "-c", code], check=True, cwd=str(__import__("pathlib").Path(entry.__file__).parent))
