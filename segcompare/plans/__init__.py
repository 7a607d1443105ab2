"""Batch schemes, work packing, rebalancing and measures."""
