"""Operators for preparing text corpora: packing, fingerprints, deduplication, scans, tokenising."""
