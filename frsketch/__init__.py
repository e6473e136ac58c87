"""Mergeable set-resemblance sketches as Spark DataFrames."""
