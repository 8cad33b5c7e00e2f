"""Training-data operators: tokenization, extraction, deduplication, search, mixing.

Nothing outside this folder (and ``corpus_pipeline.py``) imports it.
"""
