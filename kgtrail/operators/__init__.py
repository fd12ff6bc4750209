"""Part of kgtrail."""
