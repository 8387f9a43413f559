"""Operators of a training-data pipeline (ten methods), kept apart from the filter engine.

Nothing outside this subpackage imports it; ``queries.py`` registers its queries.
"""
