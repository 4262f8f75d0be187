"""All queries of the library outside the llm subpackage, with their SQL."""

from __future__ import annotations

from cubegrid import statistics, workloads
from cubegrid.functions import scalar, udx
from cubegrid.operators import relational
from cubegrid.streaming import windows

ENTRY = workloads.entry_query
QUERIES = {**workloads.QUERIES, **statistics.query.queries, **relational.query.queries, **scalar.query.queries, **windows.query.queries, **udx.query.queries}
ORACLE = {**workloads.ORACLE, **statistics.query.oracle, **relational.query.oracle, **scalar.query.oracle, **windows.query.oracle, **udx.query.oracle}
