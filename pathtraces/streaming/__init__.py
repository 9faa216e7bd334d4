"""Live forms over streams of readings."""
