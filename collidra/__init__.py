"""Similarity search over sparse sets by collision counting, as DataFrame plans for Spark."""
