"""Tables, derived fixtures, sinks and layouts."""
