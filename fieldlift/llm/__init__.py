"""Training-data operators: mixing, media columns, nearest neighbours, quality, near duplicates,
licence and secret scans, HTML extraction, id files and byte-pair coding.

Nothing outside this subpackage imports it; it can be deleted without touching the rest.
"""
