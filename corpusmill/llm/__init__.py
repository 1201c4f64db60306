"""Training-data operators: scans, joins, deduplication, extraction and packing.

Nothing outside this subpackage imports it.
"""
