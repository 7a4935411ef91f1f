"""A corpus pipeline of four stages over `documents`: language, toxicity, near duplicates, packing.

Each stage takes (spark, docs, sf_dir) and returns what it keeps; run() writes each result as Parquet in the shared folder and reads it again as the next
stage's docs. All stages but the last return the columns of documents. The stages themselves are in retro.llm.
"""

from retro.llm.pipeline_stages import STAGES, run

ORACLE_SQL = None  # learned scores and token ids have no SQL form

__all__ = ["ORACLE_SQL", "STAGES", "run"]
