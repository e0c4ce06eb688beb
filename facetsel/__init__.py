"""Budgeted, balanced selection of instruction data, written for Spark."""
