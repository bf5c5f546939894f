"""From raw documents to packed training sequences: the stages and their run.

``STAGES`` are (name, function) pairs; each function takes (spark, docs, sf_dir) and works on
all that the stage before it kept. ``run`` applies them to documents, writing the result of
each as Parquet and reading it again before the next.
"""

from densecount.llm.stages import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
