"""Blocks, panels, products and small dense routines."""
