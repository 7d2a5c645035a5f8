"""The affine intermediate form and the propagation methods that compile to it."""
