"""shotgrid: compression and analysis of lidar range images (grids of laser shots) on Spark."""

__version__ = "0.1.0"
