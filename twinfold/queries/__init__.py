"""Registered queries of the duplicate engine and the SQL that must give the same rows."""
