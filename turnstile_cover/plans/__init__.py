"""Parameters and experiment runs."""
