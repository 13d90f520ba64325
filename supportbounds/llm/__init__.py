"""Operators for preparing training corpora.

Nothing outside this folder imports it; the folder may be removed as a whole.
"""
