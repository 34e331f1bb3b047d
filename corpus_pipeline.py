"""The corpus pipeline: its stages, in order, what SQL says of its rows, and the run over documents. The stages
themselves are in huecount.llm.pipeline."""

from huecount.llm.pipeline import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
