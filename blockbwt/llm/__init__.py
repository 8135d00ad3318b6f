"""Operators of a training-data pipeline. Nothing outside this subpackage imports it.

Every operator takes a DataFrame and names of its columns, reads no other
column of it, and returns columns of its own, so further columns of the input,
whatever their names, neither clash nor travel.
"""
