"""Tables, vector families and sinks."""
