"""Tables, edge lists and the graph views derived from them."""
