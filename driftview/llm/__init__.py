"""Training-data operators: deduplication, filtering, scoring, archives and mixing.

Nothing else in the library imports this subpackage.  Every operator takes and
returns DataFrames, states what it does with nulls, empty and very long texts,
ties, repeated rows and empty tables in its docstring, and keeps intermediate
tables only in the folder that the session names in ``spark.checkpoint.dir``.
"""
