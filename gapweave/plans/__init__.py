"""End-to-end pipelines and experiment grids."""
