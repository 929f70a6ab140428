"""Reading tables and binding their facts to grids."""
