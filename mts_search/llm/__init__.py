"""Training-data pipeline operators (extraction, filters, deduplication, mixing, packing).

Nothing outside this subpackage, its tests and ``corpus_pipeline.py`` imports it.
"""
