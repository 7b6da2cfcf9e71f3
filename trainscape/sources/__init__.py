"""Readers, sinks and the checkpoint store."""
