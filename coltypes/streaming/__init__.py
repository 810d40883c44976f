"""Structured Streaming forms: live column profiles, drift, incremental annotation."""
