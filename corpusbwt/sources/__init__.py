"""Tables, derived string sets and the stored index as a data source."""
