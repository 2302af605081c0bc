"""Operators for building training corpora: ten operators and their queries.

Nothing outside this subpackage imports it.  Every operator takes and returns
DataFrames, keeps no driver-side copy of the data and survives lost executors:
intermediate tables go to the folder named by ``spark.checkpoint.dir``.
"""
