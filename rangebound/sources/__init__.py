"""Constructors of range frames, and files of them."""
