"""Training-data operators: language ID, near-dedup, decontamination, secrets, PII, packing and the like.

Nothing else in the library imports this subpackage; its queries live in :mod:`motifspark.llm.registry`.
"""
