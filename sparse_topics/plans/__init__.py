"""Physical choices that depend on sizes the driver knows exactly."""
