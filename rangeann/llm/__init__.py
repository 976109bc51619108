"""Operators for large text corpora used to train language models.

Nothing else in the library imports this subpackage.  Queries live in
``rangeann.llm.queries``; every operator module has a general interface of its own.
"""
