"""Training-data operators.

Nothing outside this subpackage (and the top-level ``corpus_pipeline.py``)
imports it; deleting the folder leaves the rest of the library intact.
"""
