"""labelflow: graph label propagation with count-min sketches, built on Spark DataFrames."""
