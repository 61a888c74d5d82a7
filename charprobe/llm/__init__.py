"""Training-data operators: sharding, joins, filters, packing, stores, scoring and search.

Nothing outside this subpackage imports it; ``corpus_pipeline.py`` chains five of the operators.
"""
