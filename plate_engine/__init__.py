"""Declarative Bayesian-network models with variational message passing on Spark."""
