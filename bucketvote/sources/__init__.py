"""Tables, formats and stored indexes."""
