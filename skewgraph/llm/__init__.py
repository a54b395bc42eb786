"""Operators of a large-scale training-data pipeline.

Nothing else in the library imports this subpackage.  Each module holds one operator with its own
general interface; ``queries`` derives the registered ``op<N>_<name>`` results from them.
"""
