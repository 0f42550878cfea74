"""Training-data operators: quality rules, token counts, URL filters, byte-level BPE, quality classifier,
benchmark decontamination, substring dedup, WARC archives, sharding and SimHash near-dedup.

Nothing outside this subpackage imports it.
"""
