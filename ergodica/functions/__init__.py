"""Functions for SQL users: scalar, aggregate and table functions, and views."""
