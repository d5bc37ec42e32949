"""Errors that name the offending column or parameter."""


class GraphError(ValueError):
    """A graph relation with a wrong column, type or value."""


class WeightError(ValueError):
    """Node weights that are not integers of at least 1."""


class ParameterError(ValueError):
    """A parameter outside its domain."""
