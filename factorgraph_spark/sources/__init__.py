"""Reading tables and graphs, and writing them."""
