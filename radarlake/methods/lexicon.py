"""Word lists of the caption rules: own choices, to be replaced by a user's."""

from __future__ import annotations

COLORS = ("red", "orange", "yellow", "green", "blue", "purple", "violet", "pink", "brown", "black", "white", "grey", "gray", "beige", "turquoise")
HEDGES = ("it appears that", "appears to be", "seems to be", "might be", "could be", "may be", "possibly", "probably", "perhaps", "likely", "presumably", "apparently")
#: Category: words for it, words that rule it out. The order is the priority among ties.
CATEGORIES = {
    "airport": (("airport", "runway", "airfield", "aircraft", "terminal apron"), ("seaport",)),
    "port": (("port", "harbour", "harbor", "dock", "pier", "quay", "container yard"), ("no port", "airport")),
    "rail": (("railway", "rail yard", "train", "railroad"), ("handrail",)),
    "industrial": (("factory", "industrial", "refinery", "warehouse", "power plant"), ()),
    "mining": (("mine", "quarry", "open pit", "excavation"), ("mine field",)),
    "volcano": (("volcano", "lava", "crater"), ()),
    "snow_ice": (("snow", "glacier", "ice sheet", "ice field"), ("ice cream",)),
    "desert": (("desert", "dune", "arid plain"), ()),
    "mountain": (("mountain", "ridge", "rocky slope", "peak"), ()),
    "coastal": (("coast", "beach", "shoreline", "coastline"), ()),
    "water": (("river", "lake", "reservoir", "pond", "water body"), ("no water",)),
    "urban": (("city", "urban", "building", "residential", "downtown", "suburb"), ()),
    "agriculture": (("field", "farmland", "crop", "orchard", "agricultural"), ("sports field", "airfield")),
    "vegetation": (("forest", "tree", "woodland", "shrub", "vegetation"), ()),
    "road": (("road", "highway", "interchange", "motorway"), ()),
}
#: Stand-in vocabularies for the given tables' words.
PART_CATEGORIES = {
    "machine": (("gear", "ring", "anvil"), ("hot",)),
    "joint": (("bolt", "rod"), ()),
    "surface": (("plate", "cold"), ()),
    "toy": (("gizmo", "widget", "small"), ("plate",)),
}
#: Instructions for the three lengths, in own words.
PROMPTS = {
    "short": "Name the main structures of the scene in a few words. Use no color terms and state only what is visible.",
    "mid": "Describe the main structures of the scene and how they lie to each other in one sentence. Use no color terms and state only what is visible.",
    "long": "Describe the scene in detail: structures, layout, surroundings. Use no color terms and state only what is visible.",
}
