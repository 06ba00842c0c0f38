"""All queries of the engine and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from accord.queries import experiments, flows, method, study, surface

_ = (experiments, flows, study, surface)  # they register their queries with method.query
QUERIES = {**method.Q}
ORACLES = {**method.S}
