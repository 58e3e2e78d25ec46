"""Personalised, robust federated optimisation on Spark."""
