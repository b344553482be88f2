"""Tables, unit views, sinks."""
