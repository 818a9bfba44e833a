"""Reading and writing graphs and results."""
