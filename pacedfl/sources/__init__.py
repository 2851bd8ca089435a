"""Tables, schemas, update fixtures and features."""
