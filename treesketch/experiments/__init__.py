"""The experiments and the queries that the driver runs."""
