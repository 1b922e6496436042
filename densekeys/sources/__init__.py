"""Readers and writers: key tables in any format, and artifacts as a Python data source."""
