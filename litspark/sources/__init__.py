"""Sources and sinks beside the given Parquet tables."""
