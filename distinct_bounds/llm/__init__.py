"""Operators of a training-data pipeline over a table of documents.

Nothing outside this subpackage imports it. Every operator takes a DataFrame and the
names of its id and text columns, keeps the input's columns and adds its own; where an
input column bears the name of an added one (whatever the case), the added one wins.
"""
