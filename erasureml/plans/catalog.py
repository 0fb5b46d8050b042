"""All queries of the engine and their SQL."""

from erasureml.plans import experiments, relational, streams, workloads

QUERIES = workloads.QUERIES | experiments.QUERIES | relational.QUERIES | streams.QUERIES
ORACLES = workloads.ORACLES | experiments.ORACLES | relational.ORACLES | streams.ORACLES
