"""Sketch operators over DataFrames, and the in-memory form behind them."""
