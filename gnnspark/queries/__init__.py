"""Named queries over the given tables, each with DuckDB SQL where SQL can express it."""
