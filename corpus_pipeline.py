"""The corpus pipeline of the training-data operators: its stages, its SQL (none) and its run, as the subpackage has them."""

from groupstream.llm.pipeline import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
