"""slicegrad: training and applying networks inside ordinary Spark plans."""
