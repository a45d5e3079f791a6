"""Catalogs, metadata files, a directory data source, sinks."""
