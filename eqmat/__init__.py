"""Rule materialisation under resource equality, written for Spark."""
