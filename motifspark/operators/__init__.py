"""Relational operators around mining, as queries with SQL twins."""
