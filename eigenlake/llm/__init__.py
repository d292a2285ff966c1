"""Operators for the text side of a training-data pipeline.

Nothing else in the library imports this subpackage; `queries` holds the
registered queries, `oracles` the SQL that checks them.
"""
