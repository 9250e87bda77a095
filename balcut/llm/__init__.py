"""Training-data operators: ten corpus-scale stages on DataFrames.

Nothing outside this subpackage imports it.
"""
