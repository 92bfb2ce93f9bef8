"""Two-way regular path queries over edge-labelled graphs, on Spark."""
