"""Every method, workload and operator as a query over the given tables, registered by key with its DuckDB SQL."""
