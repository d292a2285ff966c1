"""The filtered solver and its parts."""
