"""The counting methods, their preparation, and what is built on their results."""
