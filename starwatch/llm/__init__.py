"""Operators of a training-data pipeline (token counts, packing, filters, dedup).

Nothing else in the library imports this subpackage.
"""
