"""A training-data pipeline: toxicity, repeated lines, near duplicates, source mixing, packing."""

from trajdp.llm.stages import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
