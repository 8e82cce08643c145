"""Tables, derived graphs and sinks."""
