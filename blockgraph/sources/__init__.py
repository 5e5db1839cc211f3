"""Tables, graphs made of them, generated graphs, and file formats of edge lists."""
