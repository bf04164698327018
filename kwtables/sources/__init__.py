"""Tables, knowledge graphs and sinks."""
