"""The subpackage's registered queries and their SQL."""

from __future__ import annotations

from . import html_text, line_dedup, lm, mixing, near_dups, pieces, pipeline, quality, repeats, secrets, topk

QUERIES = {"pipeline": pipeline.run, "op1_piece_encode": pieces.query, "op2_secret_scan": secrets.query, "op3_mix_sources": mixing.query, "op4_quality_rules": quality.query, "op5_html_text": html_text.query, "op6_near_dups": near_dups.query, "op7_lm_score": lm.query, "op8_substring_dedup": repeats.query, "op9_exact_topk": topk.query, "op10_line_dedup": line_dedup.query}
SQL = {"op8_substring_dedup": repeats.SQL, "op9_exact_topk": topk.SQL, "op10_line_dedup": line_dedup.SQL}
