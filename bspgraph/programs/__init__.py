"""Programs written in other interfaces' styles."""
