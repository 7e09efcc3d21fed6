"""Operators for preparing large text corpora.

Nothing outside this package imports it.  Every operator takes and returns
DataFrames and keeps to the session it is given: no start-time setting is
changed, and intermediate tables go to the folder in ``spark.checkpoint.dir``.
"""
