"""Operations for large-scale training-data pipelines.

Nothing outside this subpackage imports it.  Every operator takes DataFrames
and returns a DataFrame; :mod:`delprop.llm.queries` wires them to the tables.
"""
