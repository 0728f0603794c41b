"""A corpus pipeline: language ID, line dedup, near-duplicate join, decontamination, packing. The stages are in ontospark.llm.pipeline."""

from __future__ import annotations

from ontospark.llm.pipeline import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
