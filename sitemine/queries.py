"""Registry of the core queries and the SQL that must give the same rows."""

from __future__ import annotations

from sitemine.workloads import clustering, costs, itemsets

QUERIES = {**itemsets.QUERIES, **clustering.QUERIES, **costs.QUERIES}
ORACLES = {**itemsets.ORACLES, **clustering.ORACLES, **costs.ORACLES}
