"""Pure numeric building blocks: coders, models, bit structures, size formulas."""
