"""Small networks in NumPy: reverse-mode gradients, optimiser, and the three learned components."""
