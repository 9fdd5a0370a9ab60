"""Tables, graph views over them, edge-list readers and the stored graph."""
