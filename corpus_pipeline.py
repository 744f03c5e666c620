"""The corpus pipeline: STAGES, run() and ORACLE_SQL, as defined in `pathflow/llm/pipeline.py`."""

from pathflow.llm.pipeline import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
