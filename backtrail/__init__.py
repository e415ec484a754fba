"""Query explanation on Spark: labelled evaluation, slices, replay."""
