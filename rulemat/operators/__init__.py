"""Relational operators around the rule engine, with the SQL that states what they return."""
