"""Operators for preparing training text: near-duplicates, quality, secrets, mixing, token output.

Every module here takes plain DataFrames and returns plain DataFrames; nothing
outside this subpackage imports it.
"""
