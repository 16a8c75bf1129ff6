"""Operations of a large training-data pipeline: quality, deduplication, mixing, packing, scans.

Nothing else in the library imports this subpackage.
"""
