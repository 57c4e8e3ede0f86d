"""Readers and writers of facts, rules and tables."""
