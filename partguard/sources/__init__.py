"""Tables, feature catalogs and fault plans."""
