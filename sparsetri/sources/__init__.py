"""Edge sources: graph views of tables, text and Parquet edge lists."""
