"""Tenants, costs and jobs."""
