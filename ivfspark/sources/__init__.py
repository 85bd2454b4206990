"""Sources: given tables, derived vector collections, index data source."""
