"""Reading layers, documents and triples, and writing them."""
