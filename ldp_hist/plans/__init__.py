"""Parameters, cost models, dispatch and the query catalogue."""
