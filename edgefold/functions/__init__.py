"""Step functions, activations and vector functions on columns and arrays."""
