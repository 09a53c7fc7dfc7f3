"""Operations of a training-data pipeline: scans, models, indexes, near-duplicate search, token files.

Nothing outside this subpackage imports it. Each operator has a module of its own with a general
interface (any frame, any column names); ``registry`` holds the thin queries over the given tables.
"""
