"""Distributed construction and evaluation of collision-free functions."""
