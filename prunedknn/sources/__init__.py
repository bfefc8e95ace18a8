"""Reading tables through Spark's data source interface."""
