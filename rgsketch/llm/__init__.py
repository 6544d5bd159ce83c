"""Training-data operators: decontamination, sharding, media, dedup, scans, language ID, filters and mixing.

Nothing outside this subpackage imports it.
"""
