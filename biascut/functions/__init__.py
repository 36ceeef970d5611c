"""SQL functions, table functions, aggregates and views for users of SQL."""
