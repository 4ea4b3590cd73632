"""Tables, mixed relations, derivations and the index data source."""
