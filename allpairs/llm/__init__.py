"""Operators for preparing training text at corpus scale.

Every module is one operator with a general interface; ``queries`` holds the
thin registered queries.  Nothing outside this subpackage imports it.
"""
