"""Sandboxed execution of SQL text and plan-level signals."""
