"""Rule-based information extraction that can speak about the layout of a page, on Spark."""
