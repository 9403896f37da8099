"""Plans that put operators together: grids of codecs and the evaluation of them."""
