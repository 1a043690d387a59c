"""Operators that prepare large text corpora for language-model training.

Nothing else in :mod:`locpref` imports this subpackage. Every operator takes and
returns DataFrames; :mod:`locpref.llm.queries` holds the thin registered queries.
"""
