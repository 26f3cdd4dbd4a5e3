"""Cost and accuracy measures: bounds, theory, access cost, communication, timing."""
