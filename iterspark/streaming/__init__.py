"""Mini-batch workflows and stream operators."""
