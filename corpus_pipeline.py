"""The corpus pipeline: STAGES, run(spark, sf_dir) and ORACLE_SQL, from the subpackage that holds the operators."""

from tidegraph.llm.pipeline import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
