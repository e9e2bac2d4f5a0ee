"""Row-major grids, cell mappings and the regridding methods."""
