"""Registered plans: the engine's queries and, beside each, the SQL that must agree with it."""
