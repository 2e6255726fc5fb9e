"""Training-data operators: sharding, chat formatting, deduplication, licence scans,
fingerprints, decontamination, quality and toxicity models, Jaccard joins and packing.

Nothing outside this subpackage imports it; ``llm.queries`` holds the registered queries.
"""
