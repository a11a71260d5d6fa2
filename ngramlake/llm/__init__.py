"""Operations of a training-data pipeline: packing, search, dedup, filters, mixing.

Nothing outside this folder imports it.  ``queries.py`` and ``sql.py`` hold the
registered queries and their DuckDB counterparts.
"""
