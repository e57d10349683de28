"""Optimisers that exchange lossy gradients."""
