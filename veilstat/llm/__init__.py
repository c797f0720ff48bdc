"""Training-data operators: packing, deduplication, token counts, PII, encoding, quality, id files.

Nothing outside this folder imports it; ``veilstat.llm.queries`` lists its queries.
"""
