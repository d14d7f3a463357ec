"""Training-data operators: language ID, sharding, BPE, packing, deduplication,
vector search, quality and toxicity. Nothing outside this folder imports it."""
