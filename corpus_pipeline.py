"""The corpus pipeline: stages over documents, each one written as Parquet and reread by the next."""

from __future__ import annotations

from coordsketch.llm import pipeline as _p

STAGES = _p.STAGES
run = _p.run
ORACLE_SQL = None  # it holds a tokenizer, hashes and a trained classifier; a test compares each stage with a plain version
