"""Training-data operators: search, joins, packing, scans, mixing and archives.

Nothing outside this subpackage imports it, so it can be removed whole.
"""
