"""Tables, clustered layouts and the pruning data source."""
