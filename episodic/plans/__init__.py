"""Level-wise mining: candidates, culling, the choice of a counting method, evolution over slices."""
