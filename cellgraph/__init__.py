"""Out-of-core graph analytics on Spark: vertex bands, destination-sorted edge cells, vertex programs."""
