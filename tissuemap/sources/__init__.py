"""Tables, schemas, generators, readers and sinks."""
