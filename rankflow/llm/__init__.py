"""Training-data operators: mixing, quality, fingerprints, near duplicates,
toxicity, token files, sub-word pieces, licences, shards and media columns.

Nothing outside this subpackage imports it.
"""
