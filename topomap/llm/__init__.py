"""Training-data operators: quality, near-duplicate, mixing, sharding and token stages.

Nothing outside this folder imports it; its queries are in ``llm.catalogue``.
"""
