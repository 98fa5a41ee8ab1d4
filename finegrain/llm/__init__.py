"""Operators of a training-data pipeline; nothing else in ``finegrain`` imports this subpackage."""
