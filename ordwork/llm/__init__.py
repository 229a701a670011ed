"""Operations of a training-data pipeline: filters, deduplication, tokenisation.

Nothing else in the library imports this subpackage.
"""
