"""The reference's workloads and operator queries on the given tables."""

from deltafold.workloads import incremental, iterative, operators

QUERIES: dict = {**incremental.QUERIES, **operators.QUERIES, **iterative.QUERIES}
ORACLE_SQL: dict = {**incremental.ORACLE_SQL, **operators.ORACLE_SQL, **iterative.ORACLE_SQL}
