"""Neighbour lists, partitions, borders, bond graphs and the layers that run over them."""
