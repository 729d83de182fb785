"""Tables, files and the filter wire format."""
