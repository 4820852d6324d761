"""A PySpark engine that finds frequent waveforms (motifs) in large collections of sensor series."""
