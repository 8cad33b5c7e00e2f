"""Reachability: set-level operators with one interface, and the indexes behind them."""
