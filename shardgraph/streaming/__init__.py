"""Structured Streaming forms of the methods and of event reports."""
