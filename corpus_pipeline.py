"""The corpus pipeline; its stages are in momentbuf.llm.pipeline."""

from momentbuf.llm.pipeline import COLUMNS, ORACLE_SQL, STAGES, near_duplicates, packing, repeated_strings, run, secret_scans, toxicity

__all__ = ["COLUMNS", "ORACLE_SQL", "STAGES", "near_duplicates", "packing", "repeated_strings", "run", "secret_scans", "toxicity"]
