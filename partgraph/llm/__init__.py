"""Training-data operators: one module for each, digest queries in ``catalog``."""
