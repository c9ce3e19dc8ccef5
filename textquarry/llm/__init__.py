"""Training-data operators: personal data, near duplicates, quality, search, secrets, toxicity,
line dedup, byte-level BPE, fingerprints and packing.

Nothing outside this subpackage imports it.
"""
