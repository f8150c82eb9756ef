"""Zonal statistics of rasters over polygons, on Spark DataFrames."""
