"""Standing pattern queries on evolving labelled graphs, on Spark."""
