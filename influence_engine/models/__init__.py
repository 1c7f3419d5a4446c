"""Models whose gradients are indexed."""
