"""Tensor-compiled scoring of classical predictive pipelines on Spark."""
