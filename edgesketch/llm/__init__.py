"""Training-data operators: ten text operators and the queries that apply them.

Nothing outside this subpackage imports it; ``__spark_entry__.py`` adds its queries only
when it can be imported.
"""
