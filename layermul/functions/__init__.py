"""User-defined semirings and the SQL surface."""
