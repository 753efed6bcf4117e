"""Labelled pages that the tree never sees: "+" main text, "-" anything else."""

CASES = (
    "<html><body><div><a>-Start page</a> | <a>-Sitemap</a></div><h1>+Why bees dance</h1><div>+A bee that has found flowers comes home and walks a figure of eight on the comb, over and over, shaking as she goes.</div><div>+The angle is the angle to the sun.</div><div>+How long she shakes tells how far it is, and the others, who cannot see her in the dark, feel it with their feet.</div><div><a>-All texts on insects</a></div><div><a>-All texts on birds</a></div><div>-This site is run by volunteers. <a>-Give</a> <a>-Help</a></div></body></html>",
    "<body><article class='post with-sidebar'><h1>+A quiet street</h1><p>+Number nine has been empty since spring, and the grass has grown through the gate.</p><p>+Number ten has a new door</p></article></body>",
    "<body><p>+There were three of them, and none of the three would say who had opened the window.</p></body>",
    "<body><header><a>-Blog</a></header><div id=content><p>+Today I sorted screws.</p><p>+By length</p><p>+By thread</p><p>+Then the cat came.</p></div><div class='comment-list'><article class='comment'><p>-Mine does that too, whenever I open the drawer with the small things in it.</p></article></div></body>",
    "<body><ul><li><a>-Rooms</a></li><li><a>-Prices</a></li><li><a>-Booking</a></li></ul><div>-Call us any time</div><p>+The house was built as a mill and still has its wheel, which turns when the river is high and keeps some of our guests awake.</p><p>+Breakfast is at eight, or when you come down.</p><p>+Dogs are welcome in all rooms but the red one, where the carpet is older than the house and has been eaten once already.</p><ul><li><a>-How to get here</a></li><li><a>-Leave a review</a></li></ul><div>-Mill House, River Lane</div></body>",
    "<body><div>-We and our partners use cookies to measure visits. <a>-Refuse</a> <a>-Accept</a></div><div><a>-Front page</a></div><div><a>-Politics</a></div><div><a>-Money</a></div><h1>+Bridge to stay closed</h1><p>+The bridge at the old ford will stay closed until the autumn, the county said, since two of its six piers have moved in the flood.</p><p>+Buses go round by the dam.</p><p>+The county had first hoped to open one lane in July, but divers found a third pier to be hollow, and the plan was dropped.</p><div><a>-More on the flood</a></div><div><a>-Pictures of the week</a></div><div><a>-Crossword</a></div><div>-All rights reserved</div></body>",
    "<body><main><h1>+Release notes</h1><ul><li>+faster start</li><li>+fewer crashes</li><li><a>+issue 12</a></li></ul><p>+Thanks to all.</p></main><footer>-Made in Oslo. We do not track you.</footer></body>",
    "<body><h2>+Stone soup</h2><p>+A soldier came to a village with nothing but a pot, and the village had nothing either, or so it said.</p><p>+He asked for a stone.</p><p>+\"And salt?\"</p><p>+Salt was found, and then a carrot, and by evening there was soup for all of them and a little left for the dog.</p></body>",
    "<body><div class='breadcrumbs'>-Home / Garden / Soil</div><div class=entry><p>+Clay holds water and sand lets it go, and most gardens have some of each.</p><p>+Try it: wet a handful and roll it</p><p><a>+A table of soils</a></p></div><div class='widget recent'><h4>-Recent posts</h4><p>-How we made a pond, part two, with pictures and a list of all that went wrong.</p></div></body>",
    "<body><div><a>-Login</a> <a>-Register</a></div><div>-Thread 8812</div><div><a>-kettle_fan</a></div><div>+The switch of mine has failed after a year as well, and the maker told me that the part is not sold any more, though the kettle is.</div><div>+I bent the contact back with pliers.</div><div>+It has worked since then, for four months and some two cups a day, but I would not leave the room while it is on.</div><div><a>-Reply</a> <a>-Report</a></div><div><a>-Next thread</a></div></body>",
)
