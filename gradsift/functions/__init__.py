"""Functions and views for SQL users."""

from gradsift.functions.sqlapi import register  # noqa: F401
