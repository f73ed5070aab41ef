"""Training-data operators: sharding, near-dedup, repeated passages, URL rules,
toxicity, language, decontamination, mixing, personal data, quality rules.

Nothing outside this subpackage imports it.
"""
