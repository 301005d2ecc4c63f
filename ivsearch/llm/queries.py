"""Queries over the given tables, one for each operator, and SQL that gives the same rows where SQL can."""

from __future__ import annotations

from . import graph_ann, language_id, line_dedup, mixing, ngram_join, packing, quality_classifier, quality_rules, sharding, token_files

QUERIES = {
    "op1_line_dedup": line_dedup.op1_line_dedup,
    "op2_ngram_jaccard_join": ngram_join.op2_ngram_jaccard_join,
    "op3_packing": packing.op3_packing,
    "op4_mixing": mixing.op4_mixing,
    "op5_sharding": sharding.op5_sharding,
    "op6_quality_classifier": quality_classifier.op6_quality_classifier,
    "op7_language_id": language_id.op7_language_id,
    "op8_token_files": token_files.op8_token_files,
    "op9_graph_ann": graph_ann.op9_graph_ann,
    "op10_quality_rules": quality_rules.op10_quality_rules,
}
SQL = {"op4_mixing": mixing.SQL}
