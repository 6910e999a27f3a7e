"""Composite methods: Gram matrices, least squares, factorisation, recommendation, folds."""
