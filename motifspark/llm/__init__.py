"""Operators of a training-data pipeline, each by one named method.

Nothing else in the library imports this subpackage.  ``registry`` lists the
queries and their SQL twins.
"""
