"""Training-data operators for corpora: quality, duplicates, contamination, privacy, packing and storage.

Nothing outside this folder imports it.
"""
