"""catalogflow: ingestion, de-duplication and labelling of item catalogues on Spark."""
