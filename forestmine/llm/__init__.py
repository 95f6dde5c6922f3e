"""Operators for preparing text corpora at scale.

Nothing outside this folder imports it; the registry module ``registry`` lists
its queries and their SQL.
"""
