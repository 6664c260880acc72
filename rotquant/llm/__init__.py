"""Training-data operators (token counts to licence scans) and their queries.

Nothing outside this folder imports it; the entry module adds ``queries()`` and
``oracle_sql()`` of ``rotquant.llm.registry`` when the folder is present.
"""
