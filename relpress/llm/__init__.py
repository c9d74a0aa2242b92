"""Training-data operators: ten independent corpus operators and their contract queries.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its queries when it is present.
"""
