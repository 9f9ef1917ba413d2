"""Training-data operators: each module holds one operator, its driver query and, where SQL can say it, its SQL.

Nothing outside this folder imports it; ``__spark_entry__`` adds :func:`queries` and :func:`oracle_sql` when it is there.
"""
