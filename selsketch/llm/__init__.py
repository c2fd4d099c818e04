"""Training-data operators (WARC, dedup, packing, scans, quality).

Nothing else in the library imports this subpackage; it can be removed without touching the rest.
"""
