"""Tables, graph mappings, dictionaries, formats, shared scratch."""
