"""Operations of a training-data pipeline over document, conversation and benchmark tables.

Nothing else in :mod:`meshpack` imports this subpackage.  Every operator takes and
returns DataFrames; :mod:`meshpack.llm.queries` holds the thin registered queries.
"""
