"""From raw documents to training shards, in five stages: quality classifier, near duplicates, benchmark decontamination, mix, shards.

STAGES lists (name, function of (spark, docs, sf_dir)); run(spark, sf_dir) applies them to documents. See rankloom/llm/pipeline.py.
"""

from rankloom.llm.pipeline import ORACLE_SQL, STAGES, run

__all__ = ["ORACLE_SQL", "STAGES", "run"]
