"""Operations of a training-data pipeline: formatting, deduplication, filtering, mixing, search and binary output.

Nothing outside this subpackage imports it.
"""
