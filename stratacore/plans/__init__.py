"""Measures, experiments and the SQL that checks them."""
