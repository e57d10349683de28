"""Choices of layout, codec and exchange."""
