"""Plans: which method runs, with what settings, on which engine, and the experiments made of them."""
