"""Operators for preparing language-model training data, each by one named method.

Nothing outside this subpackage imports it; ``__spark_entry__.py`` adds its
queries only when it can be imported.
"""
