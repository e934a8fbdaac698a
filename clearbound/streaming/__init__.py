"""Structured Streaming forms of the audit and of the verdict monitor."""
