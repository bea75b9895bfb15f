"""Training-data operators that stand beside the gradient engine.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its queries
when it is present.
"""
