"""Training-data operators: dedup, token counts, packing, scans and scoring for text corpora.

Nothing outside this subpackage (and ``corpus_pipeline.py``) imports it.
"""
