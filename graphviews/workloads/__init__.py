"""Registered workloads and the SQL that checks them."""
