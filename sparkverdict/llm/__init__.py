"""Operators of a training-data pipeline; each module holds one operator and nothing outside imports them."""
