"""Registered queries, by theme, each with the SQL it is compared with."""
