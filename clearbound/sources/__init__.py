"""Tables, formats and the fixtures made from the given tables."""
