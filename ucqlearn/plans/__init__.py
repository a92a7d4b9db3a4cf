"""Query descriptions, table mapping and training plans."""
