"""Operators for the preparation of training data; nothing else in nestdep imports this."""
