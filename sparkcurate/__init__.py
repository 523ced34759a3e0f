"""Training-data curation on Spark."""
