"""Operators of a training-data pipeline: one module per operator, ``entries`` collects their queries."""
