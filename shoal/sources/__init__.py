"""Tables, files, generators."""
