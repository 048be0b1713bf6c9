"""Adapters from tables to update logs, matrices and feature tables."""
