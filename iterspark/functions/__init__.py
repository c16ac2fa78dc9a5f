"""Features, learners and measures."""
