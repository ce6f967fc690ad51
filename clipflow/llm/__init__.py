"""Training-data operators: licences, duplicates, shards, packing, contamination, toxicity, urls.

Nothing outside this folder (and ``corpus_pipeline.py``) imports it.
"""
