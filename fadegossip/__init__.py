"""Time-fading heavy hitters over many sites, as a PySpark engine."""
