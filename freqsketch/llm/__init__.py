"""Training-data operators (packing, deduplication, mixing, token files, filters).

Nothing outside this subpackage and ``corpus_pipeline.py`` imports it.
"""
