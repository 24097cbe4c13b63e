"""Tables, object collections and sinks."""
