"""Operators of a training-data pipeline. Nothing else in rankflow imports this subpackage."""
