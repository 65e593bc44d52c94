"""Training-data operators: dedup, decontamination, archives, sharding, mixing, scoring, chat formatting.

Nothing outside this subpackage imports it; the entry module adds its queries only when it is present.
"""
