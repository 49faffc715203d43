"""Registered queries by theme, each with the SQL that gives the same rows where SQL can."""
