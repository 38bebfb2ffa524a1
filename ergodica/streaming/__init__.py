"""Transition counts from streams, and stationary vectors that follow them."""
