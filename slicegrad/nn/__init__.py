"""Small networks on NumPy, run inside Arrow batches."""
