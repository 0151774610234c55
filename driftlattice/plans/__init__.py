"""Mining plans: lattices, variants, windows, theory, measures."""
