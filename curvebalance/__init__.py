"""Curve-ordered partitioning, balancing and search of weighted point sets on Spark DataFrames."""
