"""Choosing, dispatching and running whole mining plans."""
