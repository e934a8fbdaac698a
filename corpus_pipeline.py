"""The corpus pipeline, whose stages are in clearbound.llm.pipeline."""

from clearbound.llm.pipeline import COLUMNS, ORACLE_SQL, STAGES, run

__all__ = ["COLUMNS", "ORACLE_SQL", "STAGES", "run"]
