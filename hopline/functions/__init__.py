"""Hash randomness, global ranks, parameter settings and bounds."""
