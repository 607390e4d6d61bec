"""Registered queries by theme, each with the SQL that says the same where SQL can."""
