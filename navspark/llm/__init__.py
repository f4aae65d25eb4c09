"""Corpus preparation operators.

Nothing outside this subpackage imports it; it may be deleted as a whole.
"""
