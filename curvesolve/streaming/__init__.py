"""Heartbeats as streams: cycles, failure rates, outages, slice states, late and repeated results."""
