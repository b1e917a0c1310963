"""Training-data operators: PII, decontamination, near-dedup, toxicity, token counts,
quality rules, substring dedup, packing, quality classifier, URL filters.

Nothing outside this folder imports it.
"""
