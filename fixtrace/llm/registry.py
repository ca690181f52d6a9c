"""Queries of this subpackage and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from fixtrace.llm.extraction import op3_tree_scoring_extraction
from fixtrace.llm.licenses import op6_license_rules
from fixtrace.llm.lines import OP7_SQL, op7_line_runs
from fixtrace.llm.mixing import op10_raked_mixture
from fixtrace.llm.mixing import oracle as op10_sql
from fixtrace.llm.ngrams import OP4_SQL, op4_parity_join
from fixtrace.llm.packing import op2_hierarchical_packing
from fixtrace.llm.quality import op1_quality_classifier
from fixtrace.llm.rules import OP9_SQL, op9_rule_ledger
from fixtrace.llm.vectors import OP5_SQL, op5_cell_links
from fixtrace.llm.urls import OP8_SQL, op8_url_sweep


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_quality_classifier, op2_hierarchical_packing, op3_tree_scoring_extraction, op4_parity_join, op5_cell_links, op6_license_rules, op7_line_runs, op8_url_sweep, op9_rule_ledger, op10_raked_mixture)}


def oracle_sql() -> dict[str, str]:
    return {"op4_parity_join": OP4_SQL, "op5_cell_links": OP5_SQL, "op9_rule_ledger": OP9_SQL, "op7_line_runs": OP7_SQL, "op8_url_sweep": OP8_SQL, "op10_raked_mixture": op10_sql()}
