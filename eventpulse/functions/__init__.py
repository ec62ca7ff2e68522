"""eventpulse subpackage."""
