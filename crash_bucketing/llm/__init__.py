"""Operators for large training corpora: ten self-contained DataFrame operators over `documents`.

Nothing else in the library imports this subpackage.
"""
