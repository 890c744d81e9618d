"""Training-data operators: ten corpus operators and their registered queries.

Nothing outside this folder imports it.  ``consensus_spark.llm.registry``
holds the queries and the DuckDB statements.
"""
