"""Training-data operators that sit beside the graph engine.

Nothing outside this subpackage imports it: ``__spark_entry__`` adds its
queries only when the subpackage is present.
"""
