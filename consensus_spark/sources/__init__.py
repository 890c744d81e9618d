"""Tables, compute-time laws, communication graphs."""
