"""Training-data operators: ten dealt operators, each in a module of its own.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its queries when it can be imported.
"""
