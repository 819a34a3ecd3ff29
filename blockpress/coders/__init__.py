"""Sequential coders: plain Python and numpy, no Spark."""
