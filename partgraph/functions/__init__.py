"""Functions of the library that Spark does not have."""
