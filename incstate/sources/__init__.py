"""Tables, circuit text, sinks."""
