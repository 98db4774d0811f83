"""Training-data operators: mixing, near-dedup, sharding, decontamination and so on.

Nothing outside this subpackage imports it.
"""
