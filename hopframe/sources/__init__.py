"""File sources and sinks beside Parquet in place, and the catalog as a data source."""
