"""cutseg: graph-cut text segmentation on Spark DataFrames."""
