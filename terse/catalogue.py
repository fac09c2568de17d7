"""All queries of the training engine by name, with their SQL equivalents."""

from __future__ import annotations

from functools import partial

from terse import workloads
from terse.functions import udfs
from terse.operators import coded, relational
from terse.plans import sharded, traced
from terse.streaming import online

ITERATIONS = {name: partial(sharded.query, name=name) for name in sharded.PLANS}

QUERIES = ITERATIONS | coded.QUERIES | traced.QUERIES | relational.QUERIES | online.QUERIES | udfs.QUERIES | workloads.QUERIES
SQL = {name: sharded.sql(name) for name in sharded.PLANS} | coded.SQL | traced.SQL | relational.SQL | online.SQL | udfs.SQL
