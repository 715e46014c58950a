"""Part of shotgrid."""
