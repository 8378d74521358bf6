"""Tables, update streams and the view store."""
