"""Criteria, planning and the registered queries."""
