"""Point sources: tables, generators, files."""
