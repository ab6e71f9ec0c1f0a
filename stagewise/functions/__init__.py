"""Functions of steps, and search spaces made of them."""
