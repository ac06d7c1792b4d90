"""Tables, object sets, index files and the data source."""
