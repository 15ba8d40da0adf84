"""Readers, writers, graph builders and generators."""
