"""Tables, planted channels, streams and sinks."""
