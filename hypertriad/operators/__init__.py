"""Links, triad searches, samplers and measures."""
