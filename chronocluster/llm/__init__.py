"""Operators of a large-scale training-data pipeline over plain text tables.

Nothing outside this subpackage imports it.  Each module holds one operator with a general
interface; :mod:`chronocluster.llm.registry` derives the query results from them.
"""
