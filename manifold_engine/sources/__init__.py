"""Point recipes over tables, readers, sinks and stored models."""
