"""Structured Streaming forms of the methods and of the operators around them."""
