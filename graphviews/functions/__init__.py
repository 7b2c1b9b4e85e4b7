"""Functions beside the built-in ones: a bag median, a hierarchy expander, a keyed outer change."""
