"""Tables in and out: Parquet, text formats, views, samples, staged results."""
