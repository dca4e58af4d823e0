"""Tables, index storage and the compressed-list data source."""
