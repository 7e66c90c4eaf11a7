"""Operators of a training-data pipeline: extraction, licences, token files, similarity joins, mixing, chat, search.

Nothing else in the library imports this subpackage. Every operator takes and returns DataFrames; Python kernels
run on Arrow batches, and intermediate tables go to the folder that the session names in ``spark.checkpoint.dir``.
"""
