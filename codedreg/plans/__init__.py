"""Training plans: which strategy runs the epochs, and the loop that runs them."""
