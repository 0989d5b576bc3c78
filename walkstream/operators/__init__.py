"""Graph, push, walk, repair and query operators."""
