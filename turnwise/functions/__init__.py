"""Functions over ids and graphs: locality, cache simulation, Arrow functions."""
