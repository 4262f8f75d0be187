"""Operators of a training-data pipeline: mixing, near-duplicate joins, WARC, decontamination,
token counts, GIF media columns, line and byte-level deduplication, quality and language models.

Nothing outside this subpackage imports it; ``registry`` holds its queries.
"""
