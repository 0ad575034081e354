"""The query catalogue: each query with the DuckDB SQL that checks it."""
