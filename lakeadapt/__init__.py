"""lakeadapt: moves column typers between data lakes, written for Spark from the start."""

__version__ = "0.1.0"
