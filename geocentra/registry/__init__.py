"""Queries of the graph engine by name, and their DuckDB SQL."""
