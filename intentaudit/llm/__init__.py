"""Training-data operators (dedup, fingerprints, scans, scoring, mixing, packing).

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its
queries only when it can be imported.
"""
