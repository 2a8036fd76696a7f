"""Index, sampling, neighbour, cell, regression and serving methods."""
