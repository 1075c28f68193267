"""Cross-media event popularity on Spark: quantification, alignment, measures, streams."""
