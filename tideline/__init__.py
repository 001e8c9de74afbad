"""Ordered graph analytics on PySpark: algorithms that process vertices by a monotone priority.

Subpackages: ``operators`` (the ordered engine and relational graph operators), ``sources`` (tables and
graph builders), ``functions`` (column helpers), ``plans`` (schedules, legality, tuning), ``streaming``.
"""
