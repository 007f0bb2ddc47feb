"""Search-based tuning of data-cleaning pipelines on Spark."""
