"""Labels with the most distinct items, in bounded memory, on Spark."""
