"""Readers, sinks and planted panels."""
