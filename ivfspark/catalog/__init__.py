"""Queries by key, each beside the DuckDB SQL that defines its result."""
