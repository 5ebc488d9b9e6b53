"""Every method, baseline, measure, workload and operator as a query, with its SQL."""

from boxsum.workloads import experiments, methods, relational, streams  # noqa: F401  they register themselves
from boxsum.workloads.cases import ORACLE_SQL, QUERIES  # noqa: F401
