"""Operators over range frames: order, windows, algebra."""
