"""Tables and logs in, results out."""
