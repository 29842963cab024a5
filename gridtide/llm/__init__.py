"""Operators for large training-data pipelines.

Nothing outside this subpackage imports it, apart from the guarded lookup in
``__spark_entry__.py`` and the pipeline at the repository top.
"""
