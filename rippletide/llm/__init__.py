"""Training-data operators: near-duplicates, language ID, secrets, substrings,
top-k search, packing, mixing, fingerprints, quality and WARC.

Nothing outside this subpackage imports it."""
