"""Operators for preparing large text corpora.

Nothing outside this subpackage imports it: the rule engine works without it.
Every operator takes and returns DataFrames and can be run on a cluster that
loses executors: intermediate tables that are read more than once are cut off
with ``checkpoint()`` in the folder named by ``spark.checkpoint.dir``.
"""
