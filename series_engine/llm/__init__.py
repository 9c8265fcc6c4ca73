"""Operators of a training-data pipeline.

Each module holds one operator with its own general interface; ``queries`` holds
the thin query of each operator and ``oracles`` their SQL.  Nothing outside this
folder imports it.
"""
