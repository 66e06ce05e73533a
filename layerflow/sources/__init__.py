"""Tables, graphs built on them and the data source of spilled layers."""
