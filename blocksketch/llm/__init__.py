"""Operators for preparing training text at scale.

Each module holds one operator with a general interface; ``queries`` and
``sql`` hold the thin registered queries and their SQL twins.  Nothing outside
this subpackage imports it.
"""
