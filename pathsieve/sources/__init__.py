"""Tables, edge lists and the property-graph encodings built on them."""
