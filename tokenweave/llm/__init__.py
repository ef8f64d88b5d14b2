"""Operators that prepare large text collections for language-model training.

Nothing outside this subpackage imports it; the library works without it.
"""
