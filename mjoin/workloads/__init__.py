"""The experiment workloads over the given tables, each with its DuckDB SQL."""
