"""Linear sketches for L2-heavy keys whose answers stay right when later inputs depend on earlier ones."""
