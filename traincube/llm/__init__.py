"""Operators that prepare text and vector tables for model training.

Nothing else in the library imports this subpackage. Queries over the given
tables are in ``traincube.llm.queries``.
"""
