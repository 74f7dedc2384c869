"""Operators for building language-model training data on Spark.

Nothing else in the library imports this subpackage.  ``queries`` holds the
registered ``opN_*`` queries; every other module is one operator.
"""
