"""Operators of predictive pipelines: each is a pure function of its input columns after training."""
