"""clipforge: data curation, bucketing, flow-matching data paths and planning on Spark."""
