"""The training-corpus pipeline at the place where it is looked for; its stages are in blocksketch/llm/pipeline.py."""

from __future__ import annotations

from blocksketch.llm.pipeline import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
