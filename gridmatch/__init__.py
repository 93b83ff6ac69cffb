"""Region search on tiled grids, expressed as Spark DataFrame plans."""
