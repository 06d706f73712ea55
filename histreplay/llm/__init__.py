"""Training-data operators: language id, quality, mixing, token files, dedup, sharding, packing, licence scans.

Nothing outside this subpackage imports it.
"""
