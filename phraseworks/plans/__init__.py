"""The pipeline, workloads and registered queries."""
