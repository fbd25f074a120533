"""DuckDB SQL for the queries of the catalogue, written apart from the Spark plans."""
