"""Training-data operators: mixing, token counts, de-duplication, packing, search."""
