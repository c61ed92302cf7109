"""Registered queries, by topic, each beside the SQL that gives the same rows."""
