"""Readers, writers and schema dictionaries."""
