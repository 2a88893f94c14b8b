"""Training-data operators: scoring, extraction, privacy, tokenising, copies, leaks, search and sharding.

Nothing outside this folder (and ``corpus_pipeline.py``) imports it.
"""
