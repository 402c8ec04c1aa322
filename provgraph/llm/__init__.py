"""Operators of a training-data pipeline: filters, joins, tokenisation, packing.

Nothing else in the library imports this subpackage.  Every operator takes
DataFrames and column names, reads only the columns it needs (others may have
any name) and keeps whole texts and all rows.
"""
