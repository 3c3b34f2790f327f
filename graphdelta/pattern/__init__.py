"""Small query graphs and what their shape tells."""
