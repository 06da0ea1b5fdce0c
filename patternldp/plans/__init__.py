"""Budgets, protocols and mechanism plans on the driver."""
