"""Tables, graphs made from them, and stores for graphs and results."""
