"""Cost and accuracy measures."""
