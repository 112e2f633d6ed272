"""The network, its training and compression, the four tasks, baselines, measures."""
