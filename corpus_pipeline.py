"""The corpus pipeline of the subpackage llm: STAGES, run and ORACLE_SQL (see :mod:`stseq.llm.pipeline`)."""

from stseq.llm.pipeline import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
