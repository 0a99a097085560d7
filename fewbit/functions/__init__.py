"""Pure functions of the methods: draws, lattices, bit codec, bounds and ledgers, each with its SQL form."""
