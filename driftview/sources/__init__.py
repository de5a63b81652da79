"""Tables, and a view as a Spark data source."""
