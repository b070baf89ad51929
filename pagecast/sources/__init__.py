"""Series carved from tables, generated series, the model store, a data source."""
