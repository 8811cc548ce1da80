"""Choosing a budget and a method."""
