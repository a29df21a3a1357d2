"""Training-data operators: language id, mixing, near-duplicate joins, toxicity, PII, decontamination, URL rules.

Nothing outside this subpackage imports it; its queries live in :mod:`lexbridge.llm.queries`.
"""
